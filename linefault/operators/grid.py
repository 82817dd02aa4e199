"""The whole feature grid of all metrics at once, over packed series.

Learning needs every feature of every record, but only to add it up: its range, and tickets and hours by bin. So each
series is packed into one row, and a task turns a batch of series into features in numpy and at once into sums by
(feature, bin). The wide table of all features never leaves a batch, nothing but sums is shuffled, and the exponential
averages, a recursion that frames cannot express, cost one loop for all metrics and all lambdas. Scoring computes the few
selected features natively (features.build_features); both agree up to the rounding of a sum's order.

A null or NaN reading makes a window incomplete and leaves an exponential average as it was.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.naming import Feature
from ..sources.staging import staged
from .thresholds import SHIFT, STEPS, best_cuts, direction_of

KEYS, ORDER = ("device",), ("ts", "rec_id")
#: Feature values that a task holds at once.
CELLS = 2**23


def pack_series(counted: DataFrame, metrics: Sequence[str], keys=KEYS, order=ORDER, extra=("tickets", "hours")) -> DataFrame:
    """One row a series: its metrics and the extra columns as arrays of doubles in order. Staged, so that every pass over it
    is a scan without shuffle; one series must fit in memory (the records of one device in the period)."""
    names = [*dict.fromkeys([*metrics, *extra])]
    values = [F.col(n).cast("double").alias(f"v{i}") for i, n in enumerate(names)]
    points = F.array_sort(F.collect_list(F.struct(*[F.col(o).alias(f"o{i}") for i, o in enumerate(order)], *values)))
    # A stated number of partitions, which adaptive execution leaves as it is: the passes cost much more than their bytes.
    dealt = counted.repartition(int(counted.sparkSession.conf.get("spark.sql.shuffle.partitions")), *keys)
    rows = dealt.groupBy(*keys).agg(points.alias("points"))
    return staged(rows.select(*[F.col(f"points.v{i}").alias(n) for i, n in enumerate(names)]), "series")


def windowed_features(v: np.ndarray, place: np.ndarray, wins: Sequence[int]) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(win, average, weighted average, variance) of each window, all metrics (columns of v) at once.

    place is each record's number in its series. With S_w the sum of the last w values, the weighted sum is
    S_1 + ... + S_win, so both averages of all windows come from one walk back; the variance is taken from its own mean.
    """
    n, longest = len(v), max(wins)
    back = np.concatenate([np.full((longest, v.shape[1]), np.nan), v])
    lag = lambda j: back[longest - j : longest - j + n]
    total, weighted = np.zeros_like(v), np.zeros_like(v)
    wanted = set(wins)
    for j in range(longest):
        total = total + lag(j)
        weighted = weighted + total
        win = j + 1
        if win in wanted:
            short = (place < j)[:, None]
            mean = total / win
            spread = np.zeros_like(v)
            for i in range(win):
                spread += (lag(i) - mean) ** 2
            yield win, np.where(short, np.nan, mean), np.where(short, np.nan, weighted / (win * (win + 1) / 2)), np.where(short, np.nan, spread / win)


def exponential_features(v: np.ndarray, sizes: np.ndarray, lambdas: np.ndarray) -> np.ndarray:
    """(record, metric, lambda): one step for the t-th records of all series together."""
    out = np.full((*v.shape, len(lambdas)), np.nan)
    starts = np.cumsum(sizes) - sizes
    order = np.argsort(-sizes, kind="stable")
    live = np.searchsorted(-sizes[order], -np.arange(int(sizes.max(initial=0))), side="left")  # series longer than t
    state = np.full((len(sizes), v.shape[1], len(lambdas)), np.nan)
    for t, count in enumerate(live):
        at = starts[order[:count]] + t
        now, held = v[at][:, :, None], state[:count]
        moved = np.where(np.isnan(held), now, lambdas * now + (1 - lambdas) * held)
        state[:count] = np.where(np.isnan(now), held, moved)
        out[at] = state[:count]
    return out


def feature_matrix(values: dict[str, np.ndarray], sizes: np.ndarray, grid: Sequence[Feature], points_per_day: int) -> np.ndarray:
    """(feature, record) of the grid over series laid end to end; nan where a feature is undefined."""
    metrics = list(dict.fromkeys(f.metric for f in grid))
    v = np.column_stack([values[m] for m in metrics]) if metrics else np.zeros((int(sizes.sum()), 0))
    at, out = {m: i for i, m in enumerate(metrics)}, np.full((len(grid), len(v)), np.nan)
    place = np.arange(len(v)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    smooth = [(i, f) for i, f in enumerate(grid) if f.model == "ewma"]
    if smooth:
        tenths = sorted({f.param for _, f in smooth})
        found = exponential_features(v, sizes, np.array(tenths) / 10.0)
        for i, f in smooth:
            out[i] = found[:, at[f.metric], tenths.index(f.param)]
    framed = [(i, f) for i, f in enumerate(grid) if f.model != "ewma"]
    if framed:
        for win, mean, weighted, spread in windowed_features(v, place, sorted({f.param * points_per_day for _, f in framed})):
            of = {"avg": mean, "wma": weighted, "wma-diff": v - weighted, "var": spread}
            for i, f in framed:
                if f.param * points_per_day == win:
                    out[i] = of[f.model][:, at[f.metric]]
    return out


def _slices(batches, names: Sequence[str], per_record: int):
    """(values, sizes) of some whole series at a time, so that per_record numbers a record stay within CELLS."""
    for batch in batches:
        sizes = batch[names[0]].value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
        flat = {n: batch[n].flatten().to_numpy(zero_copy_only=False).astype(float) for n in names}
        ends = np.cumsum(sizes)
        first = 0
        while first < len(sizes):
            begin = ends[first] - sizes[first]
            last = max(first + 1, int(np.searchsorted(ends, begin + CELLS // max(1, per_record), side="right")))
            yield {n: x[begin : ends[last - 1]] for n, x in flat.items()}, sizes[first:last]
            first = last


def grid_summary(packed: DataFrame, grid: Sequence[Feature], points_per_day: int) -> DataFrame:
    """(feature, n, mean, f_min, f_max) of every feature; one row a feature leaves a task."""
    grid, metrics = list(grid), list(dict.fromkeys(f.metric for f in grid))
    names = pa.array([f.name for f in grid])

    def run(batches):
        n, total = np.zeros(len(grid), np.int64), np.zeros(len(grid))
        lo, hi = np.full(len(grid), np.inf), np.full(len(grid), -np.inf)
        for values, sizes in _slices(batches, metrics, len(grid)):
            x = feature_matrix(values, sizes, grid, points_per_day)
            known = ~np.isnan(x)
            n += known.sum(axis=1)
            total += np.where(known, x, 0.0).sum(axis=1)
            lo = np.minimum(lo, np.where(known, x, np.inf).min(axis=1, initial=np.inf))
            hi = np.maximum(hi, np.where(known, x, -np.inf).max(axis=1, initial=-np.inf))
        some = pa.array(n > 0)
        yield pa.RecordBatch.from_arrays([names, pa.array(n), pa.array(total), pa.array(lo), pa.array(hi)], ["feature", "n", "total", "lo", "hi"]).filter(some)

    found = packed.select(*metrics).mapInArrow(run, "feature string, n long, total double, lo double, hi double")
    return found.groupBy("feature").agg(F.sum("n").alias("n"), (F.sum("total") / F.sum("n")).alias("mean"), F.min("lo").alias("f_min"), F.max("hi").alias("f_max"))


def place_in_bins(x: np.ndarray, lo: float, hi: float, steps: int) -> np.ndarray:
    """1 plus the number of cuts at or below each value, with the cuts computed as they are printed; see thresholds._bin."""
    cut = lambda j: lo + j * (hi - lo) / steps - (hi - lo) * SHIFT
    near = np.floor((x - lo) / (hi - lo) * steps)
    exact = near + np.where(x >= cut(near + 1), 1, np.where(x < cut(near), -1, 0))
    return np.clip(exact + 1, 1, steps).astype(np.int64)


def grid_bins(packed: DataFrame, grid: Sequence[Feature], points_per_day: int, ranges: dict[str, tuple[float, float]], steps: dict[str, int]) -> DataFrame:
    """(feature, f_min, f_max, bin, tickets, hours) of all features in one pass, as thresholds.bin_totals gives for one.

    At most features x steps rows leave a task. Features without a range of some width have no bins.
    """
    grid = [f for f in grid if f.name in ranges and ranges[f.name][0] < ranges[f.name][1]]
    metrics = list(dict.fromkeys(f.metric for f in grid))
    names = [f.name for f in grid]
    if not grid:
        return packed.sparkSession.createDataFrame([], "feature string, f_min double, f_max double, bin long, tickets long, hours double")

    def run(batches):
        held = [[np.zeros(steps[n] + 1), np.zeros(steps[n] + 1), np.zeros(steps[n] + 1)] for n in names]
        for values, sizes in _slices(batches, [*metrics, "tickets", "hours"], len(grid)):
            x = feature_matrix(values, sizes, grid, points_per_day)
            for i, name in enumerate(names):
                known = ~np.isnan(x[i])
                at = place_in_bins(x[i][known], *ranges[name], steps[name])
                for own, weights in zip(held[i], (values["tickets"][known], values["hours"][known], None), strict=True):
                    own += np.bincount(at, weights, steps[name] + 1)
        for name, (tickets, hours, rows) in zip(names, held, strict=True):
            at = np.flatnonzero(rows)
            lo, hi = ranges[name]
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(at), pa.string()), pa.array(np.full(len(at), lo)), pa.array(np.full(len(at), hi)), pa.array(at), pa.array(tickets[at].astype(np.int64)), pa.array(hours[at])], ["feature", "f_min", "f_max", "bin", "tickets", "hours"])

    part = packed.select(*metrics, "tickets", "hours").mapInArrow(run, "feature string, f_min double, f_max double, bin long, tickets long, hours double")
    return part.groupBy("feature", "f_min", "f_max", "bin").agg(F.sum("tickets").alias("tickets"), F.sum("hours").alias("hours"))


def search_grid(packed: DataFrame, grid: Sequence[Feature], points_per_day: int, directions: dict[str, str] | None = None, steps: int = STEPS, band_steps: int = 40, **guards) -> DataFrame:
    """The best cut of every feature of the grid: metric, model, param, and what thresholds.search_all gives.

    Two passes over the packed series: one for all ranges, which reach the driver as one row a feature, one for all bins.
    """
    side = {f.name: (directions or {}).get(f.name) or direction_of(f.name) for f in grid}
    ranges = {r["feature"]: (r["f_min"], r["f_max"]) for r in grid_summary(packed, grid, points_per_day).collect()}
    counts = {n: band_steps if d == "band" else steps for n, d in side.items()}
    bins = staged(grid_bins(packed, grid, points_per_day, ranges, counts), "bins")
    best = best_cuts(lambda names, _: bins.where(F.col("feature").isin(names)), side, steps, band_steps, **guards)
    named = packed.sparkSession.createDataFrame([(f.name, f.metric, f.model, f.param) for f in grid], "feature string, metric string, model string, param int")
    return F.broadcast(named).join(best, "feature")
