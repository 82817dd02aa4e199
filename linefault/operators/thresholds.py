"""Thresholds that maximise the ticketing-rate ratio.

All candidates of all features come from one histogram: a first scan takes each feature's range, a second adds
tickets and hours per (feature, bin) with map-side combination, and running sums over the bins then give the four
sums of every cut. Nothing but one row per feature and the winners reach the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.naming import parse_feature
from .rates import rate_ratio

STEPS = 100
#: All cuts lie this share of the range below the even grid, so that discrete values, which often fall on the grid, are on
#: one side of a cut however their sums were rounded.
SHIFT = 1e-9
BELOW = {"snr", "unerrored"}
ABOVE = {"tx", "corrected", "uncorrectable", "t3", "t4"}


def rank_of(score: str) -> Column:
    """Order by a score, best first. What agrees to nine places is a tie, so that the order in which a sum was added up
    decides nothing."""
    return F.desc(F.round(score, 9))


def direction_of(name: str) -> str:
    """Which side of a cut is abnormal: below, above, band (both) or auto (whichever separates better)."""
    f = parse_feature(name)
    if f.model == "var":
        return "above"
    if f.model == "wma-diff" or f.metric == "rx":
        return "band"
    return "below" if f.metric in BELOW else "above" if f.metric in ABOVE else "auto"


def looks_normal(df: DataFrame, feature: str, limit: float = 1.0) -> DataFrame:
    """(skewness, kurtosis, normal): whether a feature is near enough to a normal shape for two cuts."""
    shape = df.agg(F.skewness(feature).alias("skewness"), F.kurtosis(feature).alias("kurtosis"))
    return shape.withColumn("normal", (F.abs("skewness") < limit) & (F.abs("kurtosis") < limit))


def _bin(value: Column, lo: float, hi: float, steps: int) -> Column:
    """1 plus the number of cuts at or below the value, the cuts being computed as _cumulative prints them, so that a
    verdict by a printed cut counts exactly the records that the histogram counted."""
    cut = lambda j: F.lit(lo) + j * F.lit(hi - lo) / steps - F.lit((hi - lo) * SHIFT)
    near = F.floor((value - F.lit(lo)) / F.lit(hi - lo) * steps)
    exact = near + F.when(value >= cut(near + 1), 1).when(value < cut(near), -1).otherwise(0)
    return F.greatest(F.lit(1), F.least(exact + 1, F.lit(steps)))


def bin_totals(counted: DataFrame, features: Sequence[str], steps: int = STEPS) -> DataFrame:
    """(feature, f_min, f_max, bin, tickets, hours). bin 1..steps counts equal parts of the range; the maximum is in the last."""
    ranges = counted.agg(*[F.min(f).cast("double").alias(f"lo{i}") for i, f in enumerate(features)], *[F.max(f).cast("double").alias(f"hi{i}") for i, f in enumerate(features)]).first()
    pairs = []
    for i, f in enumerate(features):
        lo, hi = ranges[f"lo{i}"], ranges[f"hi{i}"]
        usable = lo is not None and hi is not None and lo < hi
        value = F.col(f).cast("double")
        place = F.when(value.isNotNull(), _bin(value, lo, hi, steps)) if usable else F.lit(None)  # greatest and least skip nulls
        pairs.append(F.struct(F.lit(f).alias("feature"), F.lit(lo).cast("double").alias("f_min"), F.lit(hi).cast("double").alias("f_max"), place.cast("long").alias("bin")))
    long = counted.select("tickets", "hours", F.explode(F.array(*pairs)).alias("p")).where("p.bin is not null")
    return long.groupBy("p.feature", "p.f_min", "p.f_max", "p.bin").agg(F.sum("tickets").alias("tickets"), F.sum("hours").alias("hours"))


def _cumulative(bins: DataFrame, steps: int) -> DataFrame:
    """(feature, cut_no, cut, k, h, k_all, h_all): sums of all bins up to each of the cuts 0..steps."""
    feature = bins.groupBy("feature", "f_min", "f_max").agg(F.sum("tickets").alias("k_all"), F.sum("hours").alias("h_all"))
    cuts = feature.withColumn("cut_no", F.explode(F.sequence(F.lit(0), F.lit(steps))))
    filled = cuts.join(bins.select("feature", F.col("bin").alias("cut_no"), "tickets", "hours"), ["feature", "cut_no"], "left")
    along = Window.partitionBy("feature").orderBy("cut_no").rowsBetween(Window.unboundedPreceding, 0)
    width = F.col("f_max") - F.col("f_min")
    cut = F.col("f_min") + F.col("cut_no") * width / steps - width * F.lit(SHIFT)
    summed = lambda c: F.coalesce(F.sum(c).over(along), F.lit(0))
    return filled.select("feature", "cut_no", cut.alias("cut"), summed("tickets").alias("k"), summed("hours").cast("double").alias("h"), "k_all", "h_all")


def _guarded(scores: DataFrame, min_tickets: int, min_share: float, max_share: float) -> DataFrame:
    """Cuts with a ratio and enough support: a maximum resting on a few tickets, on hardly any abnormal time or on
    hardly any normal time says nothing. The neutral settings (0, 0, 1) keep every cut."""
    rated = scores.withColumn("trr", rate_ratio(*[F.col(c) for c in ("k_abn", "h_abn", "k_norm", "h_norm")]))
    whole = F.col("h_abn") + F.col("h_norm")
    enough = (F.col("k_abn") >= min_tickets) & F.col("h_abn").between(F.lit(float(min_share)) * whole, F.lit(float(max_share)) * whole)
    return rated.where(F.col("trr").isNotNull() & enough)


def cut_scores(bins: DataFrame, direction: str, steps: int = STEPS) -> DataFrame:
    """Scores of every one-sided cut. below: value < cut is abnormal; above: value >= cut, by bins."""
    c = _cumulative(bins, steps)
    down = [F.col("k"), F.col("h"), F.col("k_all") - F.col("k"), F.col("h_all") - F.col("h")]
    sums = down if direction == "below" else [down[2], down[3], down[0], down[1]]
    low, high = (F.col("cut"), F.lit(None).cast("double")) if direction == "below" else (F.lit(None).cast("double"), F.col("cut"))
    return c.select("feature", F.lit(direction).alias("direction"), low.alias("low"), high.alias("high"), *[s.alias(n) for s, n in zip(sums, ("k_abn", "h_abn", "k_norm", "h_norm"), strict=True)])


def band_scores(bins: DataFrame, steps: int = STEPS) -> DataFrame:
    """Scores of every pair of cuts lo < hi; outside the band is abnormal. steps**2 / 2 rows a feature. A band that reaches an
    end of the range has no cut there."""
    c = _cumulative(bins, steps).withColumn("cut", F.when(~F.col("cut_no").isin(0, steps), F.col("cut")))
    a = c.select("feature", F.col("cut_no").alias("i"), F.col("cut").alias("low"), F.col("k").alias("ka"), F.col("h").alias("ha"))
    b = c.select("feature", F.col("cut_no").alias("j"), F.col("cut").alias("high"), F.col("k").alias("kb"), F.col("h").alias("hb"), "k_all", "h_all")
    pairs = a.join(b, "feature").where("i < j")
    inside = F.col("kb") - F.col("ka"), F.col("hb") - F.col("ha")
    return pairs.select("feature", F.lit("band").alias("direction"), "low", "high", (F.col("k_all") - inside[0]).alias("k_abn"), (F.col("h_all") - inside[1]).alias("h_abn"), inside[0].alias("k_norm"), inside[1].alias("h_norm"))


def best_cuts(bins_of: Callable[[list[str], int], DataFrame], side: dict[str, str], steps: int = STEPS, band_steps: int = 40, min_tickets: int = 0, min_share: float = 0.0, max_share: float = 1.0) -> DataFrame:
    """The best cut of each feature: feature, direction, low, high, the four sums, trr.

    side names each feature's direction, bins_of(features, steps) their histogram. Ties go to more abnormal tickets, then
    to less abnormal time.
    """
    parts = []
    for wanted in ("below", "above"):
        names = [f for f, d in side.items() if d in (wanted, "auto")]
        if names:
            parts.append(cut_scores(bins_of(names, steps), wanted, steps))
    names = [f for f, d in side.items() if d == "band"]
    if names:
        parts.append(band_scores(bins_of(names, band_steps), band_steps))
    best = Window.partitionBy("feature").orderBy(rank_of("trr"), F.desc("k_abn"), F.round("h_abn", 6), "direction", "low", "high")
    return _guarded(reduce(DataFrame.unionByName, parts), min_tickets, min_share, max_share).withColumn("place", F.row_number().over(best)).where("place = 1").drop("place")


def search_all(counted: DataFrame, features: Sequence[str], directions: dict[str, str] | None = None, steps: int = STEPS, band_steps: int = 40, **guards) -> DataFrame:
    """best_cuts of features that are columns of counted (underscored names). For the whole grid see grid.search_grid."""
    directions = directions or {}
    side = {f: directions.get(f) or direction_of(_hyphenated(f)) for f in features}
    return best_cuts(lambda names, n: bin_totals(counted, names, n), side, steps, band_steps, **guards)


def _hyphenated(column: str) -> str:
    head, param = column.rsplit("_", 1)
    for model in ("wma_diff", "ewma", "avg", "wma", "var"):
        if head.endswith(f"_{model}"):
            return f"{head[: -len(model) - 1]}-{model.replace('_', '-')}-{param}"
    raise ValueError(f"not a feature column: {column}")


def search_threshold(counted: DataFrame, feature: str, direction: str = "below", steps: int = STEPS, **guards) -> DataFrame:
    return search_all(counted, [feature], {feature: direction}, steps, **guards)


def search_band(counted: DataFrame, feature: str, steps: int = 40, **guards) -> DataFrame:
    return search_all(counted, [feature], {feature: "band"}, band_steps=steps, **guards)


def symmetric_band(counted: DataFrame, feature: str, widths: Sequence[float] = (1.0, 1.5, 2.0, 2.5, 3.0)) -> DataFrame:
    """Bands mean +- k standard deviations, one row per width: all in one scan after the moments."""
    m = counted.agg(F.avg(feature).alias("m"), F.stddev_pop(feature).alias("s")).first()
    mean, spread = (m["m"] or 0.0), (m["s"] or 0.0)
    options = F.array(*[F.struct(F.lit(mean - k * spread).alias("low"), F.lit(mean + k * spread).alias("high")) for k in widths])
    side = (F.col(feature) < F.col("o.low")) | (F.col(feature) > F.col("o.high"))
    from .rates import split_rates

    return counted.select(feature, "tickets", "hours", F.explode(options).alias("o")).groupBy("o.low", "o.high").agg(*split_rates(side)).withColumn("trr", rate_ratio(*[F.col(c) for c in ("k_abn", "h_abn", "k_norm", "h_norm")]))


def abnormal(feature: str, low: float | None, high: float | None) -> Column:
    """The verdict of one threshold: outside [low, high). Null values are not abnormal."""
    below = F.col(feature) < F.lit(low) if low is not None else F.lit(False)
    above = F.col(feature) >= F.lit(high) if high is not None else F.lit(False)
    return F.coalesce(below | above, F.lit(False))
