"""Smoothing a metric into features: windowed averages, variance, and exponential averages.

All windowed features of all metrics share one partitioning and one order, so the plan has one exchange
and one sort whatever the grid. Frames count records; days become records through points_per_day.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.naming import Feature

KEYS, ORDER = ("device",), ("ts", "rec_id")


def _frame(win: int, keys: Sequence[str], order: Sequence[str]):
    return Window.partitionBy(*keys).orderBy(*order).rowsBetween(1 - win, 0)


def _full(metric: str, win: int, value: Column, keys, order, partial: str) -> Column:
    """value where the window holds `win` measured points, or everywhere with partial='shrink'."""
    if partial == "shrink":
        return value
    return F.when(F.count(metric).over(_frame(win, keys, order)) == win, value)


def moving_average(metric: str, win: int, keys=KEYS, order=ORDER, partial: str = "null") -> Column:
    return _full(metric, win, F.avg(metric).over(_frame(win, keys, order)), keys, order, partial)


def weighted_average(metric: str, win: int, keys=KEYS, order=ORDER, denominator: str = "normalised", partial: str = "null") -> Column:
    """Linear weights, the newest point the heaviest. With row number r the weighted sum is
    sum(r v) - (r_now - win) sum(v), two sliding sums. 'normalised' divides by the sum of the weights;
    'printed' by win (win - 1) / 2, null for win = 1."""
    frame = _frame(win, keys, order)
    row = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    weighted = F.sum(F.col(f"{metric}__r")).over(frame) - (row - win) * F.sum(metric).over(frame)
    total = {"normalised": win * (win + 1) / 2, "printed": win * (win - 1) / 2}[denominator]
    if partial == "shrink" and denominator == "normalised":
        n = F.least(row, F.lit(win))
        return F.try_divide(weighted, F.lit(float(win)) * n - n * (n - 1) / 2)
    return _full(metric, win, F.try_divide(weighted, F.lit(float(total))), keys, order, partial)


def moving_variance(metric: str, win: int, keys=KEYS, order=ORDER, partial: str = "null") -> Column:
    return _full(metric, win, F.var_pop(metric).over(_frame(win, keys, order)), keys, order, partial)


def add_exponential(df: DataFrame, wanted: Sequence[Feature], keys=KEYS, order=ORDER) -> DataFrame:
    """Exponential averages of all metrics and lambdas in one grouped pass: a recursion that frames cannot express.

    A null value leaves the average as it was. One series is held in memory at a time; columns that take no part stay in
    Arrow as they are.
    """
    from .grid import exponential_features

    if not wanted:
        return df
    metrics, tenths = list(dict.fromkeys(f.metric for f in wanted)), sorted({f.param for f in wanted})
    kind = T.StructType(df.schema.fields + [T.StructField(f.column, T.DoubleType()) for f in wanted])

    def run(part: pa.Table) -> pa.Table:
        part = part.sort_by([(o, "ascending") for o in order])
        v = np.column_stack([part[m].cast(pa.float64()).to_numpy() for m in metrics])
        found = exponential_features(v, np.array([len(v)]), np.array(tenths) / 10.0)
        for f in wanted:
            part = part.append_column(f.column, pa.array(found[:, metrics.index(f.metric), tenths.index(f.param)], from_pandas=True))
        return part

    return df.groupBy(*keys).applyInArrow(run, kind)


def exponential_fold(metric: str, lam: float, history: str) -> Column:
    """The same average over an array of a short series' values, without Python."""
    first = F.element_at(history, 1)
    return F.aggregate(F.slice(history, 2, F.greatest(F.size(history) - 1, F.lit(0))), first, lambda acc, v: F.lit(lam) * v + F.lit(1 - lam) * acc)


def build_features(df: DataFrame, grid: Sequence[Feature], points_per_day: int, keys=KEYS, order=ORDER, denominator: str = "normalised", partial: str = "null") -> DataFrame:
    """df with one DOUBLE column per feature of the grid (named by Feature.column)."""
    out = add_exponential(df, [f for f in grid if f.model == "ewma"], keys, order)
    windowed = [f for f in grid if f.model != "ewma"]
    if not windowed:
        return out
    helpers = {f"{m}__r": m for m in dict.fromkeys(f.metric for f in windowed if f.model in ("wma", "wma-diff"))}
    row = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    if helpers:
        out = out.withColumn("__row", row).withColumns({h: F.col("__row") * F.col(m) for h, m in helpers.items()})

    def column(f: Feature) -> Column:
        win = f.param * points_per_day
        if f.model == "avg":
            return moving_average(f.metric, win, keys, order, partial)
        if f.model == "var":
            return moving_variance(f.metric, win, keys, order, partial)
        smooth = weighted_average(f.metric, win, keys, order, denominator, partial)
        return smooth if f.model == "wma" else F.col(f.metric) - smooth

    return out.withColumns({f.column: column(f) for f in windowed}).drop("__row", *helpers)


def range_average(metric: str, days: int, keys=KEYS, ts: str = "ts") -> Column:
    """Average over calendar days instead of records; ts must be TIMESTAMP or is cast to it."""
    seconds = F.col(ts).cast("timestamp").cast("long")
    return F.avg(metric).over(Window.partitionBy(*keys).orderBy(seconds).rangeBetween(1 - days * 86_400, 0))


def counter_delta(metric: str, keys=KEYS, order=ORDER) -> Column:
    """Increase of a cumulative counter; after a reset the counter itself counts."""
    before = F.lag(metric).over(Window.partitionBy(*keys).orderBy(*order))
    return F.when(F.col(metric) >= before, F.col(metric) - before).when(before.isNotNull(), F.col(metric))


def resample_hold(df: DataFrame, metric: str, start: str, end: str, every_hours: int, keys=KEYS, order=ORDER) -> DataFrame:
    """(keys, slot, value): the value in force at each slot of a regular grid over [start, end)."""
    step = F.expr(f"interval {int(every_hours)} hours")
    lo, hi = F.lit(start).cast("timestamp_ntz"), F.lit(end).cast("timestamp_ntz")
    slots = df.select(*keys).distinct().withColumn("slot", F.explode(F.sequence(lo, hi - step, step)))
    points = df.select(*keys, F.col("ts"), *[F.col(c).alias(f"o_{c}") for c in order[1:]], F.col(metric).alias("value"), F.lit(0).alias("is_slot"))
    grid = slots.select(*keys, F.col("slot").alias("ts"), *[F.lit(None).cast(dict(df.dtypes)[c]).alias(f"o_{c}") for c in order[1:]], F.lit(None).cast("double").alias("value"), F.lit(1).alias("is_slot"))
    along = Window.partitionBy(*keys).orderBy("ts", "is_slot", *[f"o_{c}" for c in order[1:]]).rowsBetween(Window.unboundedPreceding, 0)
    held = points.unionByName(grid).withColumn("held", F.last("value", ignorenulls=True).over(along))
    return held.where("is_slot = 1").select(*keys, F.col("ts").alias("slot"), F.col("held").alias("value"))
