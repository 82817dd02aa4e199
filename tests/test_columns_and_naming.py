import pytest
from pyspark.sql import functions as F

from linefault.functions import columns as C
from linefault.functions.naming import Feature, feature_grid, parse_feature


def test_grid_has_37_features_a_metric():
    grid = feature_grid([f"m{i}" for i in range(9)])
    assert len(grid) == 333
    assert len({f.column for f in grid}) == 333


@pytest.mark.parametrize("name", ["snr-var-2", "rx-wma-diff-4", "t3-avg-7", "tx-ewma-3"])
def test_names_round_trip(name):
    assert parse_feature(name).name == name


def test_bad_name():
    with pytest.raises(ValueError):
        parse_feature("snr-median-2")
    assert Feature("rx", "wma-diff", 4).column == "rx_wma_diff_4"


def test_rate_model(spark):
    row = spark.range(1).select(
        C.rate_model(*[F.lit(float(x)) for x in (1, 4, 100, 0, 0, 10)]).alias("clean"), C.rate_model(*[F.lit(float(x)) for x in (1, 4, 100, 1, 0, 10)]).alias("fp"), C.rate_model(*[F.lit(float(x)) for x in (1, 4, 100, 0, 1, 10)]).alias("fn"),
        C.rate_model_limit(F.lit(1.0), F.lit(4.0)).alias("limit"), *[c.alias(n) for c, n in zip(C.rate_model_slopes(*[F.lit(float(x)) for x in (1, 4, 100, 1, 1, 10)]), ("s1", "s2"))],
    ).first()
    assert row.clean == pytest.approx(5.0) == row.limit
    assert row.fp < 5 and row.fn < 5 and row.s1 < 0 and row.s2 < 0


def test_tap_ratio(spark):
    df = spark.createDataFrame([([1.0, 0.0, 0.1, 0.0],), ([1.0, 0.0, 0.0, 0.0],)], "t array<double>")
    got = [r[0] for r in df.select(C.tap_ratio_db("t", 0)).collect()]
    assert got[0] == pytest.approx(20.0) and got[1] is None
