"""The tools that the detector is compared with: colour bands, points scoreboard, tap-ratio rule and raw limits."""

from __future__ import annotations

from collections.abc import Sequence
from typing import NamedTuple

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import fired, ratio


class Band(NamedTuple):
    """Limits of one raw metric: inside green is fine, inside yellow is a warning, beyond is red."""

    metric: str
    green_lo: float
    green_hi: float
    yellow_lo: float
    yellow_hi: float


class Rule(NamedTuple):
    """Points given when a raw metric is below or above a limit."""

    metric: str
    side: str
    limit: float
    points: float


def quantile_bands(train: DataFrame, metrics: Sequence[str], outer: float = 0.01, inner: float = 0.05, exact: bool = False) -> list[Band]:
    """Bands at quantiles of the training data, since operators' own limits are not public."""
    marks = [outer, inner, 1 - inner, 1 - outer]
    q = (lambda m: F.percentile(m, F.array(*[F.lit(x) for x in marks]))) if exact else (lambda m: F.percentile_approx(m, F.lit(marks), 10_000))
    row = train.agg(*[q(m).alias(m) for m in metrics]).first()
    return [Band(m, row[m][1], row[m][2], row[m][0], row[m][3]) for m in metrics]


def colour_bands(df: DataFrame, bands: Sequence[Band], alarm: Sequence[str] = ("yellow", "red")) -> DataFrame:
    """df with level (worst colour over the metrics), fired and abnormal."""
    worst = F.lit(0)
    tests = []
    for b in bands:
        v = F.col(b.metric)
        code = F.when(v.isNull() | v.between(b.green_lo, b.green_hi), 0).when(v.between(b.yellow_lo, b.yellow_hi), 1).otherwise(2)
        worst = F.greatest(worst, code)
        tests.append((b.metric, code > 0))
    level = F.element_at(F.array(*[F.lit(x) for x in ("green", "yellow", "red")]), worst + 1)
    return df.withColumn("level", level).withColumn("fired", fired(tests)).withColumn("abnormal", F.col("level").isin(list(alarm)))


def band_rules(bands: Sequence[Band], points: float = 1.0) -> list[Rule]:
    """One point for each side of each metric's green range."""
    return [r for b in bands for r in (Rule(b.metric, "below", b.green_lo, points), Rule(b.metric, "above", b.green_hi, points))]


def scoreboard(df: DataFrame, rules: Sequence[Rule], limit: float = 1.0) -> DataFrame:
    """df with points, fired and abnormal: an alarm when the points exceed the limit."""
    total = F.lit(0.0)
    tests = []
    for r in rules:
        hit = F.coalesce(F.col(r.metric) < r.limit if r.side == "below" else F.col(r.metric) > r.limit, F.lit(False))
        total = total + F.when(hit, F.lit(float(r.points))).otherwise(0.0)
        tests.append((f"{r.metric} {r.side}", hit))
    return df.withColumn("points", total).withColumn("fired", fired(tests)).withColumn("abnormal", F.col("points") > limit)


def tap_ratio_flags(df: DataFrame, limit_db: float = 18.0, ratio_col: str = "tap_db") -> DataFrame:
    """df with abnormal: the main tap stands out by less than the limit."""
    return df.withColumn("abnormal", F.coalesce(F.col(ratio_col) < limit_db, F.lit(False)))


def flagged_share(flags: DataFrame, day: str = "day", approximate: bool = False) -> DataFrame:
    """(day, devices, flagged, share) of each day, and over all days in the row whose day is null."""
    count = F.approx_count_distinct if approximate else F.count_distinct
    some = F.when(F.col("abnormal"), F.col("device"))
    out = flags.rollup(day).agg(count("device").alias("devices"), count(some).alias("flagged"))
    return out.withColumn("share", ratio(F.col("flagged"), F.col("devices")))


def raw_limit(df: DataFrame, metric: str, low: float | None = None, high: float | None = None) -> DataFrame:
    """df with abnormal by a single unsmoothed reading."""
    below = F.col(metric) < low if low is not None else F.lit(False)
    above = F.col(metric) > high if high is not None else F.lit(False)
    return df.withColumn("abnormal", F.coalesce(below | above, F.lit(False)))
