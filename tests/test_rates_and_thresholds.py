import datetime as dt

import pytest
from pyspark.sql import functions as F

from linefault.operators import rates as R
from linefault.operators import thresholds as T
from linefault.plans import base as Q
from linefault.sources import adapters as A

DAY = dt.datetime(2024, 1, 1)


@pytest.fixture(scope="module")
def counted(spark, sf):
    return Q.counted(spark, sf).persist()


def test_reference_counts(spark, sf):
    tel, tk = A.telemetry(spark, sf), A.tickets(spark, sf)
    assert tel.count() == 799 and tel.where("maint").count() == 29 and tel.where("serv").count() == 35
    assert tk.count() == 201 and tk.where("is_network").count() == 47


def test_reference_ratios(counted):
    got = {c: R.trr(counted, F.col("snr") < c).first() for c in (27, 28, 29)}
    assert {c: (round(r.trr, 3), r.k_abn) for c, r in got.items()} == {27: (2.35, 8), 28: (2.261, 8), 29: (2.372, 10)}
    assert round(R.trr(counted, F.col("maint") | F.col("serv")).first().trr, 3) == 2.735


def test_sides_add_up(counted):
    whole = counted.agg(F.sum("tickets").alias("k"), F.sum("hours").alias("h")).first()
    for cut in (20, 30, 36):
        r = R.trr(counted, F.col("snr") < cut).first()
        assert r.k_abn + r.k_norm == whole.k and r.h_abn + r.h_norm == pytest.approx(whole.h)


def test_curve_adds_up(counted):
    whole = counted.agg(F.sum("tickets").alias("k"), F.sum("hours").alias("h")).first()
    for bins in (None, 10):
        r = R.rate_curve(counted, "snr", bins).agg(F.sum("tickets").alias("k"), F.sum("hours").alias("h")).first()
        assert r.k == whole.k and r.h == pytest.approx(whole.h)


@pytest.mark.parametrize("direction", ["below", "above"])
def test_search_equals_scan(counted, direction):
    best = T.search_threshold(counted, "snr", direction, 20, min_tickets=5).first()
    lo, hi = counted.agg(F.min("snr"), F.max("snr")).first()
    rows = counted.select("snr", "tickets", "hours").collect()
    found = []
    for j in range(1, 20):
        cut = lo + j * (hi - lo) / 20
        ab = [r for r in rows if (r.snr < cut) == (direction == "below")]
        no = [r for r in rows if (r.snr < cut) != (direction == "below")]
        ka, ha, kn, hn = sum(r.tickets for r in ab), sum(r.hours for r in ab), sum(r.tickets for r in no), sum(r.hours for r in no)
        if ka >= 5 and ha and hn and kn:
            found.append(((ka / ha) / (kn / hn), ka))
    assert best.trr == pytest.approx(max(found)[0])


def test_cut_verdict_matches_histogram(counted):
    best = T.search_threshold(counted, "snr", "below", 37, min_tickets=5).first()
    assert R.trr(counted, T.abnormal("snr", best.low, best.high)).first().k_abn == best.k_abn


def test_band_is_at_least_as_good(counted):
    one = T.search_threshold(counted, "snr", "below", 20, min_tickets=5).first().trr
    assert T.search_band(counted, "snr", 20, min_tickets=5).first().trr >= one - 1e-9


def test_no_ratio_without_tickets(spark):
    rows = spark.createDataFrame([(float(i), 0, 1.0) for i in range(10)], "v double, tickets long, hours double")
    assert T.search_threshold(rows, "v").count() == 0
    assert R.trr(rows, F.col("v") < 5).first().trr is None


def test_backward_hold_and_gap(spark):
    rows = spark.createDataFrame([(1, 1, i, DAY + dt.timedelta(hours=h)) for i, h in enumerate((0, 4, 30))], "device long, account long, rec_id long, ts timestamp_ntz")
    hours = lambda **k: [r.hours for r in R.held_intervals(rows, "2024-01-03", **k).orderBy("rec_id").collect()]
    assert hours() == [4, 26, 18] and hours(hold="backward") == [0, 4, 26] and hours(max_gap_hours=10) == [4, 10, 10]


def test_negative_control(spark, sf):
    """Without the plant the true-fault flag loses its ratio."""
    rows = R.count_tickets(R.held_intervals(A.telemetry(spark, sf.replace("0.001", "0.01"), plant=False), A.PERIOD_END), A.tickets(spark, sf.replace("0.001", "0.01"), plant=False).where("is_network"))
    assert R.trr(rows, F.col("snr") < 29).first().trr < 1.6


def test_planted_features_win(spark, sf):
    d = sf.replace("0.001", "0.01")
    counted = Q.counted(spark, d)
    scores = {r.feature: r.trr for r in T.search_all(counted, ["snr", "tx", "corrected", "unerrored"], {"snr": "below", "tx": "above", "corrected": "above", "unerrored": "below"}, 40, min_tickets=20, max_share=0.25).collect()}
    assert min(scores["snr"], scores["tx"]) > max(scores["corrected"], scores["unerrored"])
