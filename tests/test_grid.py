"""The whole grid in numpy against the native features and against plain loops."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from linefault.functions.naming import feature_grid
from linefault.operators import features as FE
from linefault.operators import grid as G
from linefault.operators import thresholds as T
from linefault.plans import base as Q
from linefault.sources import adapters as A

DAY = dt.datetime(2024, 1, 1)


def plain(v, f, per_day):
    """One feature of one series by its definition."""
    out = []
    win, state = f.param * per_day, None
    for i, x in enumerate(v):
        if f.model == "ewma":
            if x == x:
                state = x if state is None else f.param / 10 * x + (1 - f.param / 10) * state
            out.append(np.nan if state is None else state)
            continue
        part = v[i - win + 1 : i + 1] if i >= win - 1 else []
        if not len(part) or any(p != p for p in part):
            out.append(np.nan)
            continue
        smooth = sum((k + 1) * p for k, p in enumerate(part)) / (win * (win + 1) / 2)
        out.append({"avg": np.mean(part), "wma": smooth, "wma-diff": x - smooth, "var": np.var(part)}[f.model])
    return out


@pytest.mark.parametrize("seed", range(3))
def test_matrix_equals_definition(seed):
    rng = np.random.default_rng(seed)
    sizes = np.array([1, 9, 0, 4, 13])
    values = {m: rng.normal(50, 9, sizes.sum()) for m in ("snr", "tx")}
    values["tx"][rng.random(sizes.sum()) < 0.1] = np.nan
    grid = feature_grid(("snr", "tx"), (1, 2, 3), (1, 5, 9))
    got = G.feature_matrix(values, sizes, grid, 2)
    ends = np.cumsum(sizes)
    for f, row in zip(grid, got, strict=True):
        want = np.concatenate([plain(values[f.metric][e - s : e], f, 2) for s, e in zip(sizes, ends, strict=True)])
        np.testing.assert_allclose(row, want, atol=1e-9)


def test_summary_equals_native(spark, sf):
    grid = feature_grid(("snr", "t3"), (1, 3), (2, 8))
    tel = A.telemetry(spark, sf).withColumn("snr", F.when(F.col("rec_id") % 17 != 0, F.col("snr")))
    got = {r.feature: (r.n, r["mean"], r.f_min, r.f_max) for r in G.grid_summary(G.pack_series(tel, ("snr", "t3"), extra=()), grid, A.POINTS_PER_DAY).collect()}
    built = FE.build_features(tel, grid, A.POINTS_PER_DAY)
    row = built.agg(*[F.array(F.count(f.column), F.avg(f.column), F.min(f.column), F.max(f.column)).alias(f.column) for f in grid]).first()
    for f in grid:
        assert got[f.name] == pytest.approx(tuple(row[f.column]))


@pytest.mark.parametrize("cells", [1, 2**20])
def test_search_equals_columns(spark, sf, cells, monkeypatch):
    """The packed search gives what the search over columns gives, however many series a slice holds."""
    monkeypatch.setattr(G, "CELLS", cells)
    grid = feature_grid(("snr", "tx", "tap", "rx"), (1,), (5,))
    counted = Q.counted(spark, sf)
    got = {r.feature: r for r in G.search_grid(G.pack_series(counted, ("snr", "tx", "tap", "rx")), grid, A.POINTS_PER_DAY, min_tickets=3).collect()}
    built = FE.build_features(counted, grid, A.POINTS_PER_DAY).persist()
    want = {r.feature: r for r in T.search_all(built, [f.column for f in grid], min_tickets=3).collect()}
    assert len(got) == len(want) == len(grid)
    for f in grid:
        a, b = got[f.name], want[f.column]
        assert (a.direction, a.k_abn, a.k_norm) == (b.direction, b.k_abn, b.k_norm)
        assert (a.trr, a.h_abn) == pytest.approx((b.trr, b.h_abn))


def test_constant_metric_and_no_rows(spark):
    rows = spark.createDataFrame([(1, i, DAY + dt.timedelta(hours=i), 5.0, 0, 1.0) for i in range(6)], "device long, rec_id long, ts timestamp_ntz, snr double, tickets long, hours double")
    grid = feature_grid(("snr",), (1,), (5,))
    assert G.search_grid(G.pack_series(rows, ("snr",)), grid, 2).count() == 0
    assert G.search_grid(G.pack_series(rows.where("false"), ("snr",)), grid, 2).count() == 0


def test_plan_has_one_exchange(spark, sf):
    packed = Q.tel(spark, sf).repartition(4, "device").groupBy("device").agg(F.collect_list("snr").alias("snr"))
    plan = packed._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(device") == 1
