"""What the queries share: the planted tables, the fitted detector and typer, and each step that follows from them.

The detector learns from the first TRAIN_DAYS days; a fitted model is a handful of numbers, kept by application and folder.
Nothing here reads the planted truth.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import faults as FL
from ..operators import rates as R
from ..operators import selection as S
from ..sources import adapters as A
from ..sources.staging import staged
from .detector import DetectorModel, FaultDetector, FaultTyper, TyperModel

END, START = A.PERIOD_END, A.PERIOD_START
SPLIT, TRAIN_DAYS = "2024-01-20", 19
X, Y = 2, 4
GUARD = 20
TYPED_TICKETS = 5

_models: dict = {}


def tel(spark: SparkSession, d: str) -> DataFrame:
    return A.telemetry(spark, d)


def net(spark: SparkSession, d: str) -> DataFrame:
    return A.tickets(spark, d).where("is_network")


def held(spark: SparkSession, d: str, hold: str = "forward") -> DataFrame:
    return R.held_intervals(tel(spark, d), END, hold=hold)


def counted(spark: SparkSession, d: str) -> DataFrame:
    return R.count_tickets(held(spark, d), net(spark, d))


def detector() -> FaultDetector:
    return FaultDetector(A.METRICS, A.POINTS_PER_DAY, min_tickets=GUARD, min_share=0.005, max_share=0.25)


def train_scores(spark: SparkSession, d: str) -> DataFrame:
    """The best cut of each of the 333 features on the training days."""
    early = F.col("day") < TRAIN_DAYS
    return detector().scores(tel(spark, d).where(early), net(spark, d).where(early), SPLIT)


def _kept(spark: SparkSession, kind: str, d: str, make):
    key = spark.sparkContext.applicationId, kind, d
    if key not in _models:
        _models[key] = make()
    return _models[key]


def model(spark: SparkSession, d: str) -> DetectorModel:
    return _kept(spark, "detector", d, lambda: detector().keep(train_scores(spark, d)))


def verdicts(spark: SparkSession, d: str) -> DataFrame:
    """Held records with abnormal and fired, by the fitted detector."""
    return model(spark, d).transform(held(spark, d))


def marks(spark: SparkSession, d: str, x: int = X, y: int = Y, strict: bool = False) -> DataFrame:
    return S.mark_windows(verdicts(spark, d), x, y, strict)


def flt(spark: SparkSession, d: str, x: int = X, y: int = Y, extent: str = "onset") -> DataFrame:
    return FL.fault_events(marks(spark, d, x, y), END, y, extent)


def typer() -> FaultTyper:
    return FaultTyper(start=START, end=END, min_tickets=TYPED_TICKETS)


def typer_model(spark: SparkSession, d: str) -> TyperModel:
    return _kept(spark, "typer", d, lambda: typer().fit(staged(marks(spark, d), "marks"), A.tickets(spark, d)))


def periods(spark: SparkSession, d: str) -> DataFrame:
    """The device periods that the detector finds anomalous."""
    from ..operators.clusters import anomalous_periods

    return anomalous_periods(marks(spark, d), START, typer().period_hours)


def types(spark: SparkSession, d: str) -> DataFrame:
    """(device, slot, fault_type) of the anomalous periods, by the fitted cuts of both metrics."""
    return typer_model(spark, d).transform(tel(spark, d), periods(spark, d))
