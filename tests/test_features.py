import datetime as dt

import pytest
from pyspark.sql import functions as F

from linefault.functions.naming import Feature, feature_grid
from linefault.operators import features as FE
from linefault.sources import adapters as A

DAY = dt.datetime(2024, 1, 1)


def series(spark, values, device=1):
    rows = [(device, device, 1, i, DAY + dt.timedelta(hours=4 * i), None if v is None else float(v)) for i, v in enumerate(values)]
    return spark.createDataFrame(rows, "device long, account long, node int, rec_id long, ts timestamp_ntz, v double")


def run(spark, values, grid, **k):
    out = FE.build_features(series(spark, values), grid, 1, **k).orderBy("rec_id").collect()
    return {f.name: [r[f.column] for r in out] for f in grid}


GRID = [Feature("v", "avg", 3), Feature("v", "wma", 3), Feature("v", "wma-diff", 3), Feature("v", "var", 3), Feature("v", "ewma", 5)]


def test_by_hand(spark):
    got = run(spark, [1, 2, 3, 4, 5, 6], GRID)
    assert got["v-avg-3"] == [None, None, 2, 3, 4, 5]
    assert got["v-wma-3"][2] == pytest.approx((3 * 3 + 2 * 2 + 1) / 6)
    assert got["v-wma-diff-3"][5] == pytest.approx(6 - (18 + 10 + 4) / 6)
    assert got["v-var-3"][3] == pytest.approx(2 / 3)
    assert got["v-ewma-5"] == pytest.approx([1, 1.5, 2.25, 3.125, 4.0625, 5.03125])


def test_printed_denominator(spark):
    got = run(spark, [1, 2, 3], [Feature("v", "wma", 3), Feature("v", "wma", 1)], denominator="printed")
    assert got["v-wma-3"][2] == pytest.approx(14 / 3)
    assert got["v-wma-1"] == [None, None, None]


def test_constant_series(spark):
    got = run(spark, [7] * 10, GRID)
    assert set(got["v-var-3"][2:]) == {0.0} and all(abs(x) < 1e-12 for x in got["v-wma-diff-3"][2:])


def test_single_and_null(spark):
    assert run(spark, [4], GRID)["v-ewma-5"] == [4.0]
    got = run(spark, [1, None, 3, 5, 7], GRID)
    assert got["v-avg-3"] == [None, None, None, None, 5]
    assert got["v-ewma-5"] == pytest.approx([1, 1, 2, 3.5, 5.25])


def test_one_exchange_for_all_windows(spark, sf):
    grid = [f for f in feature_grid(["snr", "tx"], (1, 2, 3), ()) if f.model != "ewma"]
    plan = FE.build_features(A.telemetry(spark, sf).drop("node"), grid, 2)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("hashpartitioning(device") <= 1


def test_counter_reset_and_hold(spark):
    rows = series(spark, [5, 8, 2, 2])
    assert [r[0] for r in rows.select(FE.counter_delta("v"), "rec_id").orderBy("rec_id").collect()] == [None, 3, 2, 0]
    held = FE.resample_hold(rows, "v", "2024-01-01", "2024-01-02", 6).orderBy("slot").collect()
    assert [r["value"] for r in held] == [5, 8, 2, 2]


def test_fold_equals_grouped(spark):
    df = series(spark, [3, 1, 4, 1, 5])
    fold = df.groupBy("device").agg(F.transform(F.array_sort(F.collect_list(F.struct("ts", "v"))), lambda x: x["v"]).alias("h")).select(FE.exponential_fold("v", 0.3, "h")).first()[0]
    assert fold == pytest.approx(run(spark, [3, 1, 4, 1, 5], [Feature("v", "ewma", 3)])["v-ewma-3"][-1])
