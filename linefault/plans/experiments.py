"""The comparison of all detection methods under one window rule and one protocol, their cost, and the replay as a stream."""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.naming import feature_grid
from ..operators import baselines as B
from ..operators import learned as L
from ..operators.faults import fault_events
from ..operators.features import build_features
from ..operators.measures import fault_scores, ticket_sweep, tune_window
from ..operators.rates import count_tickets, held_intervals
from ..operators.selection import mark_windows
from ..operators.thresholds import ABOVE, BELOW, abnormal, best_cuts, bin_totals, rank_of
from ..sources.adapters import METRICS, POINTS_PER_DAY
from ..sources.staging import shared_dir, staged
from .detector import FaultDetector

WINDOW = 6
KINDS = ("tree", "forest", "svm", "svm_fourier")
SLIM = ("rec_id", "ts", "device", "account", "node", "day", "abnormal")


class Methods:
    """All methods, each with fit() and, after it, score(telemetry) -> telemetry with abnormal.

    Everything is fitted on the days before train_days. The learned baselines learn before valid_days, try the same number of
    settings each and choose on the days between; they take every raw metric and its features of one and two days.
    """

    def __init__(self, telemetry: DataFrame, tickets: DataFrame, period_end: str, train_days: int, valid_days: int):
        self.telemetry, self.tickets, self.period_end = telemetry, tickets, period_end
        self.train_days, self.valid_days = train_days, valid_days
        spark = telemetry.sparkSession
        self.train_end = spark.sql(f"SELECT CAST(TIMESTAMP_NTZ'2024-01-01' + INTERVAL {train_days} DAYS AS STRING) AS t").first()["t"]
        self.first, self.early = telemetry.where(F.col("day") < train_days), tickets.where(F.col("day") < train_days)
        self._labelled: DataFrame | None = None

    def labelled(self) -> tuple[DataFrame, list[str]]:
        extra = feature_grid(METRICS, (1, 2), ())
        if self._labelled is None:
            self._labelled = staged(build_features(L.label_from_tickets(self.telemetry, self.tickets, self.period_end), extra, POINTS_PER_DAY), "labelled")
        return self._labelled, [*METRICS, *[f.column for f in extra]]

    def detector(self) -> Callable[[], DataFrame]:
        model = FaultDetector(METRICS, POINTS_PER_DAY, min_tickets=20, min_share=0.005, max_share=0.25).fit(self.first, self.early, self.train_end)
        return lambda: model.transform(self.telemetry)

    def bands(self) -> Callable[[], DataFrame]:
        limits = B.quantile_bands(self.first, METRICS)
        return lambda: B.colour_bands(self.telemetry, limits)

    def scoreboard(self) -> Callable[[], DataFrame]:
        rules = B.band_rules(B.quantile_bands(self.first, METRICS))
        return lambda: B.scoreboard(self.telemetry, rules)

    def raw(self) -> Callable[[], DataFrame]:
        """The best limit of a single unsmoothed metric, found as the detector's are."""
        counted = staged(count_tickets(held_intervals(self.first, self.train_end), self.early).select(*METRICS, "tickets", "hours"), "raw")
        side = {m: "below" if m in BELOW else "above" if m in ABOVE else "band" for m in METRICS}
        best = best_cuts(lambda names, n: bin_totals(counted, names, n), side, min_tickets=20, min_share=0.005, max_share=0.25).orderBy(rank_of("trr"), "feature").first()
        test = abnormal(best["feature"], best["low"], best["high"]) if best else F.lit(False)
        return lambda: self.telemetry.withColumn("abnormal", test)

    def learned(self, kind: str) -> Callable[[], DataFrame]:
        rows, inputs = self.labelled()
        day = F.col("day")
        sample = L.balance(rows.where(day < self.valid_days))
        valid = rows.where((day >= self.valid_days) & (day < self.train_days))
        scored, _ = L.train_and_predict(kind, sample, valid, rows, inputs)
        return lambda: scored

    def all(self) -> dict[str, Callable[[], Callable[[], DataFrame]]]:
        own = {"detector": self.detector, "bands": self.bands, "scoreboard": self.scoreboard, "raw": self.raw}
        return own | {k: (lambda k=k: self.learned(k)) for k in KINDS}


def compare_methods(telemetry: DataFrame, tickets: DataFrame, period_end: str, train_days: int = 19, valid_days: int = 13, y: int = WINDOW, scope: str = "node") -> DataFrame:
    """(method, x, y, faults, accuracy, coverage, ntr) of the detector and every baseline on the days from train_days on.
    Each method's x is the best on the training days by the same rule."""
    methods = Methods(telemetry, tickets, period_end, train_days, valid_days)
    late, parts = tickets.where(F.col("day") >= train_days), []
    for name, fit in methods.all().items():
        slim = staged(fit()().select(*SLIM), name)
        early = held_intervals(slim.where(F.col("day") < train_days), methods.train_end)
        chosen = tune_window(ticket_sweep(early, methods.early, (y,), methods.train_end, scope=scope).where("x > 0")).first()
        x = int(chosen["x"]) if chosen else y
        test = held_intervals(slim.where(F.col("day") >= train_days), period_end)
        faults = fault_events(mark_windows(test, x, y), period_end, y)
        parts.append(fault_scores(faults, late, test, scope).select(F.lit(name).alias("method"), F.lit(x).alias("x"), F.lit(y).alias("y"), "faults", "accuracy", "coverage", "ntr"))
    return reduce(DataFrame.unionByName, parts)


def timed_methods(telemetry: DataFrame, tickets: DataFrame, period_end: str, train_days: int = 19, valid_days: int = 13) -> DataFrame:
    """(method, train_seconds, score_seconds): wall-clock of learning, and of scoring every record."""
    methods = Methods(telemetry, tickets, period_end, train_days, valid_days)
    methods.labelled()  # shared by the learned baselines, so part of none
    rows = []
    for name, fit in methods.all().items():
        began = time.monotonic()
        score = fit()
        fitted = time.monotonic()
        score().select(*SLIM).write.format("noop").mode("overwrite").save()
        rows.append((name, round(fitted - began, 3), round(time.monotonic() - fitted, 3)))
    return telemetry.sparkSession.createDataFrame(rows, "method string, train_seconds double, score_seconds double")


def replayed(spark: SparkSession, telemetry: DataFrame, model, x: int, y: int, points_per_day: int, chunks: int = 3) -> DataFrame:
    """The telemetry, written in `chunks` parts of the period one after another and read as a stream, through the monitor."""
    import uuid

    from ..sources.readers import TELEMETRY, stream_records
    from ..streaming.monitor import monitor, write_upserts

    folder = f"{shared_dir(spark)}/linefault-stage/{uuid.uuid4().hex}"
    rows = telemetry.select([f.name for f in TELEMETRY.fields])
    lo, hi = telemetry.agg(F.min("day").alias("lo"), F.max("day").alias("hi")).first()
    lo, hi = lo or 0.0, hi or 0.0
    for i in range(chunks):
        begin, end = lo + i * (hi - lo) / chunks, lo + (i + 1) * (hi - lo) / chunks if i < chunks - 1 else float("inf")
        part = rows.where((telemetry["day"] >= begin) & (telemetry["day"] < end))
        part.coalesce(1).write.mode("append").parquet(f"{folder}/in")
    thresholds = [r.asDict() for r in model.thresholds.collect()]  # the few selected features
    stream = monitor(stream_records(spark, f"{folder}/in", TELEMETRY), thresholds, x, y, points_per_day)
    write_upserts(stream, f"{folder}/out", f"{folder}/check").awaitTermination()
    return spark.read.schema("device long, rec_id long, ts timestamp, abnormal boolean, hits long, marked boolean, dispatch boolean").parquet(f"{folder}/out")
