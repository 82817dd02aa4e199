"""The learner and its model, and the fault typer: thin over the operators, shaped like estimators."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import period_of
from ..functions.naming import Feature, feature_grid, parse_feature
from ..operators import clusters as K
from ..operators.faults import fault_events
from ..operators.features import build_features
from ..operators.rates import count_tickets, held_intervals
from ..operators.grid import pack_series, search_grid
from ..operators.selection import classify, mark_windows, pick_features
from ..sources.readers import save_model


@dataclass
class DetectorModel:
    """Selected thresholds (feature, low, high, trr, ...) and how to compute their features.

    Scoring builds the selected features only, so a scan reads just their metrics.
    """

    thresholds: DataFrame
    points_per_day: int
    keys: Sequence[str] = ("device",)
    order: Sequence[str] = ("ts", "rec_id")

    def features(self) -> list[Feature]:
        return [parse_feature(r["feature"]) for r in self.thresholds.orderBy(F.desc("trr"), "feature").collect()]

    def transform(self, telemetry: DataFrame, rule: str = "or", at_least: int = 1) -> DataFrame:
        """telemetry with the selected features, fired and abnormal."""
        built = build_features(telemetry, self.features(), self.points_per_day, self.keys, self.order)
        return classify(built, self.thresholds, rule, at_least)

    def faults(self, telemetry: DataFrame, x: int, y: int, period_end: str, extent: str = "onset", strict: bool = False) -> DataFrame:
        verdicts = held_intervals(self.transform(telemetry), period_end, keys=self.keys, order=self.order)
        return fault_events(mark_windows(verdicts, x, y, strict, self.keys, self.order), period_end, y, extent, self.keys, self.order)

    def save(self, path: str, form: str = "json") -> None:
        save_model(self.thresholds, path, form)


@dataclass
class FaultDetector:
    """Learns thresholds for a grid of features from unlabelled telemetry and network tickets."""

    metrics: Sequence[str]
    points_per_day: int
    n_features: int = 5
    days: Sequence[int] = tuple(range(1, 8))
    tenths: Sequence[int] = tuple(range(1, 10))
    steps: int = 100
    min_tickets: int = 0
    min_share: float = 0.0
    max_share: float = 1.0
    keys: Sequence[str] = ("device",)
    order: Sequence[str] = ("ts", "rec_id")
    directions: dict[str, str] = field(default_factory=dict)

    def scores(self, telemetry: DataFrame, tickets: DataFrame, period_end: str) -> DataFrame:
        """The best threshold of every feature of the grid, named."""
        grid = feature_grid(self.metrics, self.days, self.tenths)
        counted = count_tickets(held_intervals(telemetry, period_end, keys=self.keys, order=self.order), tickets)
        packed = pack_series(counted, self.metrics, self.keys, self.order)
        return search_grid(packed, grid, self.points_per_day, self.directions, self.steps, min_tickets=self.min_tickets, min_share=self.min_share, max_share=self.max_share)

    def keep(self, scores: DataFrame) -> DetectorModel:
        """The model of the n_features best of the scores."""
        chosen = pick_features(scores, self.n_features)
        rows = chosen.collect()  # n_features rows
        return DetectorModel(scores.sparkSession.createDataFrame(rows, chosen.schema), self.points_per_day, self.keys, self.order)

    def fit(self, telemetry: DataFrame, tickets: DataFrame, period_end: str) -> DetectorModel:
        return self.keep(self.scores(telemetry, tickets, period_end))


@dataclass
class TyperModel:
    cuts: dict[str, float]
    start: str
    end: str
    every_hours: int = 12
    linkage: str = "average"
    similarity: str = "pearson"
    min_group: int = 2
    combine: str = "any"
    period_hours: int = 72
    look_back_hours: int = 168

    def types(self, telemetry: DataFrame, periods: DataFrame, metric: str, cuts: Sequence[float]) -> DataFrame:
        """clusters of the anomalous periods (device, slot) by one metric, with fault_type, at every cut."""
        vectors = K.device_vectors(telemetry, metric, self.start, self.end, self.every_hours, periods, self.period_hours, self.look_back_hours)
        return K.type_faults(K.cluster_devices(vectors, cuts, self.linkage, self.similarity), self.min_group)

    def transform(self, telemetry: DataFrame, periods: DataFrame) -> DataFrame:
        """(device, slot, fault_type) of the anomalous periods, from all metrics together."""
        typed = [self.types(telemetry, periods, m, [cut]).select("device", "slot", "fault_type") for m, cut in self.cuts.items()]
        return reduce(lambda a, b: K.combine_types(a, b, self.combine, ("device", "slot")), typed)


@dataclass
class FaultTyper:
    """Finds each metric's similarity cut by the maintenance rate ratio, without labels."""

    metrics: Sequence[str] = ("snr", "tx")
    start: str = ""
    end: str = ""
    every_hours: int = 12
    grid: Sequence[float] = tuple(round(0.05 * i, 2) for i in range(20))
    linkage: str = "average"
    similarity: str = "pearson"
    min_group: int = 2
    min_tickets: int = 0
    period_hours: int = 72
    look_back_hours: int = 168

    def model(self, cuts: dict[str, float]) -> TyperModel:
        return TyperModel(cuts, self.start, self.end, self.every_hours, self.linkage, self.similarity, self.min_group, period_hours=self.period_hours, look_back_hours=self.look_back_hours)

    def impaired(self, marks: DataFrame, tickets: DataFrame) -> DataFrame:
        """The collection periods of the marked records, with the maintenance tickets that fall in them."""
        timed = held_intervals(marks, self.end, hold="backward")
        counted = count_tickets(timed, tickets.where("is_maintenance"), hold="backward")
        return counted.where("marked").select("device", period_of("ts", self.start, self.period_hours).alias("slot"), "tickets", "hours")

    def scores(self, marks: DataFrame, tickets: DataFrame, metric: str) -> DataFrame:
        """trr_m of every cut of the grid; each node's merge tree of a period is built once. marks: telemetry with marked."""
        periods = K.anomalous_periods(marks, self.start, self.period_hours)
        typed = self.model({}).types(marks, periods, metric, self.grid)
        return K.maintenance_ratio(typed, self.impaired(marks, tickets), self.min_tickets)

    def fit(self, marks: DataFrame, tickets: DataFrame) -> TyperModel:
        cuts = {}
        for metric in self.metrics:
            best = K.best_cut(self.scores(marks, tickets, metric)).collect()
            cuts[metric] = best[0]["cut"] if best else max(self.grid)
        return self.model(cuts)


def choose_feature_count(scores: DataFrame, telemetry: DataFrame, tickets: DataFrame, points_per_day: int, most: int, x: int, y: int, period_end: str) -> DataFrame:
    """(n, trr, accuracy, coverage, ntr) for 1..most selected features: what decides how many to keep."""
    from ..operators.measures import fault_scores
    from ..operators.rates import trr

    out = None
    ranked = pick_features(scores, most)
    rows = ranked.collect()
    spark = telemetry.sparkSession
    counted = count_tickets(held_intervals(telemetry, period_end), tickets)
    for n in range(1, len(rows) + 1):
        model = DetectorModel(spark.createDataFrame(rows[:n], ranked.schema), points_per_day)
        verdicts = model.transform(counted)
        faults = fault_events(mark_windows(verdicts, x, y), period_end, y)
        row = fault_scores(faults, tickets, verdicts).select(F.lit(n).alias("n"), trr(verdicts, F.col("abnormal")).select("trr").scalar().alias("trr"), "faults", "accuracy", "coverage", "ntr")
        out = row if out is None else out.unionByName(row)
    return spark.createDataFrame([], "n int, trr double, faults long, accuracy double, coverage double, ntr double") if out is None else out
