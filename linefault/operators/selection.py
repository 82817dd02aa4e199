"""Feature selection, verdicts, and the x-of-y window that turns verdicts into marks."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import fired
from .thresholds import abnormal, rank_of

KEYS, ORDER = ("device",), ("ts", "rec_id")


def _best(scores: DataFrame, groups: Sequence[str], k: int) -> DataFrame:
    order = Window.partitionBy(*groups).orderBy(rank_of("trr"), F.asc("feature"))
    return scores.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).drop("place")


def pick_representatives(scores: DataFrame) -> DataFrame:
    """Of each metric and model, the hyper-parameter with the best ratio."""
    return _best(scores, ["metric", "model"], 1)


def pick_top_models(scores: DataFrame, k: int = 2) -> DataFrame:
    """Of each metric, the k best models."""
    return _best(scores, ["metric"], k)


def pick_features(scores: DataFrame, n: int = 5) -> DataFrame:
    """The n best of what both stages leave, ranked."""
    left = pick_top_models(pick_representatives(scores))
    return left.orderBy(rank_of("trr"), F.asc("feature")).limit(n)


def classify(df: DataFrame, model: DataFrame, rule: str = "or", at_least: int = 1) -> DataFrame:
    """df with abnormal and fired, by the thresholds of the model (a few rows, turned into literals).

    rule: 'or' (one suffices), 'and' (all), or 'k' (at_least of them).
    """
    rows = model.orderBy(F.desc("trr"), "feature").select("feature", "low", "high").collect()
    tests = [(r["feature"], abnormal(r["feature"].replace("-", "_"), r["low"], r["high"])) for r in rows]
    return combine(df, tests, rule, at_least)


def combine(df: DataFrame, tests: Sequence[tuple[str, Column]], rule: str = "or", at_least: int = 1) -> DataFrame:
    need = {"or": 1, "and": max(1, len(tests)), "k": at_least}[rule]
    named = df.withColumn("fired", fired(tests))
    return named.withColumn("abnormal", F.size("fired") >= need)


def window_counts(verdicts: DataFrame, ys: Sequence[int], keys=KEYS, order=ORDER) -> DataFrame:
    """verdicts with hits_<y>: abnormal records among the last y, for every y in one window pass."""
    along = Window.partitionBy(*keys).orderBy(*order)
    flag = F.col("abnormal").cast("int")
    return verdicts.withColumns({f"hits_{y}": F.sum(flag).over(along.rowsBetween(1 - y, 0)) for y in ys})


def mark_windows(verdicts: DataFrame, x: int, y: int, strict: bool = False, keys=KEYS, order=ORDER) -> DataFrame:
    """verdicts with hits and marked: at least x (or with strict more than x) of the last y are abnormal."""
    counted = window_counts(verdicts, [y], keys, order).withColumnRenamed(f"hits_{y}", "hits")
    return counted.withColumn("marked", F.col("hits") > x if strict else F.col("hits") >= x)


def time_split(df: DataFrame, begin: str, middle: str, end: str, resume: str | None = None, ts: str = "ts") -> tuple[DataFrame, DataFrame]:
    """[begin, middle) and [resume or middle, end), half open, so partition columns and row groups prune."""
    at = lambda x: F.lit(x).cast("timestamp_ntz")
    between = lambda a, b: df.where((F.col(ts) >= at(a)) & (F.col(ts) < at(b)))
    return between(begin, middle), between(resume or middle, end)
