import datetime as dt

import pytest
from pyspark.sql import functions as F

from linefault.operators import faults as FL
from linefault.operators import measures as M
from linefault.operators import selection as S
from linefault.operators.rates import held_intervals
from linefault.plans import base as Q

DAY = dt.datetime(2024, 1, 1)
END = "2024-01-03"


def verdicts(spark, flags, device=1, node=1):
    rows = [(device, device, node, 100 * device + i, DAY + dt.timedelta(hours=4 * i), f == "1") for i, f in enumerate(flags)]
    return held_intervals(spark.createDataFrame(rows, "device long, account long, node int, rec_id long, ts timestamp_ntz, abnormal boolean"), END)


def hours(ts):
    return (ts - DAY).total_seconds() / 3600


def spans(spark, flags, x, y, **k):
    strict, extent = k.get("strict", False), k.get("extent", "onset")
    out = FL.fault_events(S.mark_windows(verdicts(spark, flags), x, y, strict), END, y, extent).orderBy("onset").collect()
    return [(hours(r.onset), hours(r.end), r.open) for r in out]


def test_fault_limits(spark):
    flags = "0011011100"
    assert spans(spark, flags, 2, 3) == [(12, 36, False)]
    assert spans(spark, flags, 2, 3, extent="span") == [(4, 36, False)]
    assert spans(spark, flags, 2, 3, strict=True) == [(28, 32, False)]
    assert spans(spark, flags, 3, 3) == [(28, 32, False)]
    assert spans(spark, "0000000011", 1, 1) == [(32, 48, True)]
    assert spans(spark, "0000", 1, 2) == []


def tickets(spark, rows):
    return spark.createDataFrame([(i, a, DAY + dt.timedelta(hours=h)) for i, (a, h) in enumerate(rows)], "ticket_id long, account long, created timestamp_ntz")


def test_scopes(spark):
    both = verdicts(spark, "0111100000", 1).unionByName(verdicts(spark, "0011110000", 2))
    faults = FL.fault_events(S.mark_windows(both, 1, 1), END, 1)
    t = tickets(spark, [(1, 6)])
    device, node = M.fault_scores(faults, t, both).first(), M.fault_scores(faults, t, both, "node").first()
    assert (device.faults, device.accuracy) == (2, 0.5) and (node.faults, node.accuracy) == (1, 1.0)
    assert device.coverage == 1.0


def test_everything_faulty_has_rate_one(spark):
    v = verdicts(spark, "1111111111")
    faults = FL.fault_events(S.mark_windows(v, 0, 3), END, 3)
    r = M.fault_scores(faults, tickets(spark, [(1, 5), (1, 20)]), v).first()
    assert r.ntr == pytest.approx(1.0) and r.coverage == 1.0


def test_nothing_faulty_is_undefined(spark):
    v = verdicts(spark, "0000")
    r = M.fault_scores(FL.fault_events(S.mark_windows(v, 1, 1), END, 1), tickets(spark, [(1, 5)]), v).first()
    assert r.accuracy is None and r.ntr is None and r.coverage == 0


def test_jaccard(spark):
    make = lambda a, b: spark.createDataFrame([(1, DAY + dt.timedelta(hours=a), DAY + dt.timedelta(hours=b))], "device long, onset timestamp_ntz, end timestamp_ntz")
    r = M.fault_time_jaccard(make(0, 4), make(2, 5)).first()
    assert (r.both_hours, r.any_hours, r.jaccard) == (2, 5, 0.4)
    assert M.fault_time_jaccard(make(0, 4), make(0, 4)).first().jaccard == 1


@pytest.fixture(scope="module")
def fixed(spark, sf):
    return S.combine(Q.held(spark, sf), [("snr", F.col("snr") < 29)]).persist()


@pytest.mark.parametrize("scope", ["device", "node"])
def test_sweep_equals_single_settings(spark, sf, fixed, scope):
    t = Q.net(spark, sf)
    got = {(r.y, r.x): r for r in M.ticket_sweep(fixed, t, (1, 4, 6), Q.END, scope=scope).collect()}
    for x, y in ((1, 1), (1, 4), (2, 4), (3, 6), (0, 6)):
        one = M.fault_scores(FL.fault_events(S.mark_windows(fixed, x, y), Q.END, y), t, fixed, scope).first()
        assert (got[y, x].faults, got[y, x].accuracy, got[y, x].coverage, got[y, x].ntr) == pytest.approx((one.faults, one.accuracy, one.coverage, one.ntr))
    assert got[6, 0].ntr == pytest.approx(1)
    coverage = [got[6, x].coverage for x in range(7) if (6, x) in got]
    assert coverage == sorted(coverage, reverse=True)


def test_reference_setting(spark, sf, fixed):
    one = M.fault_scores(FL.fault_events(S.mark_windows(fixed, 2, 4), Q.END, 4), Q.net(spark, sf), fixed).first()
    assert one.faults == 14 and round(one.accuracy, 4) == 0.5714


def test_windows_against_a_reference(spark, sf, fixed):
    t = Q.net(spark, sf)
    rows = {r.y: r for r in M.compare_windows(fixed, t, (3, 4, 6), 6, Q.END).collect()}
    assert rows[6].overlap == 1 and rows[6].jaccard == pytest.approx(1)
    faults = {y: FL.fault_events(S.mark_windows(fixed, int(r.x), y), Q.END, y) for y, r in rows.items()}
    for y in (3, 4):
        time = M.fault_time_jaccard(faults[y], faults[6]).first()
        both = M.ticket_overlap(*[FL.tickets_in_faults(faults[k], t) for k in (y, 6)]).first()
        assert (rows[y].jaccard, rows[y].overlap) == pytest.approx((time.jaccard, both.overlap))


def test_merging_in_steps(spark):
    """Scope 'all' merges within days first; the events are those of one pass."""
    rows = [(d, d, d % 3, n, DAY + dt.timedelta(hours=a), DAY + dt.timedelta(hours=b)) for n, (d, a, b) in enumerate([(1, 0, 30), (2, 20, 26), (3, 29, 31), (4, 31, 40), (5, 50, 60), (1, 59, 61), (2, 61, 62)])]
    faults = spark.createDataFrame(rows, "device long, account long, node int, fault_no int, onset timestamp_ntz, end timestamp_ntz")
    got = [(hours(r.onset), hours(r.end), r.faults, r.accounts) for r in FL.merge_simultaneous(faults, "all").orderBy("onset").collect()]
    assert got == [(0, 31, 3, [1, 2, 3]), (31, 40, 1, [4]), (50, 61, 2, [1, 5]), (61, 62, 1, [2])]


def test_agreement_by_hand(spark):
    rows = spark.createDataFrame(list(zip("aaabbb", "xxyyyy")), "a string, b string")
    r = M.cluster_agreement(rows, "a", "b").first()
    assert r.ri == pytest.approx(10 / 15)
    assert r.ari == pytest.approx((4 - 6 * 7 / 15) / ((6 + 7) / 2 - 6 * 7 / 15))
    assert M.cluster_agreement(rows, "a", "a").first().ari == 1


def test_diagnosis(spark):
    m = S.mark_windows(verdicts(spark, "0110000000"), 2, 2)
    types = spark.createDataFrame([(1, 0, "service")], "device long, slot int, fault_type string")
    named = FL.diagnose_calls(tickets(spark, [(1, 9), (1, 30)]), m, 2, types=types, start="2024-01-01", period_hours=24).orderBy("ticket_id").collect()
    assert [r.fault_type for r in named] == ["service", None]
    sent = FL.dispatch_decisions(FL.fault_events(m, END, 2), types, "2024-01-01", 24).collect()
    assert [r.technician for r in sent] == ["service"]
    got = [r.network_cause for r in FL.diagnose_calls(tickets(spark, [(1, 9), (1, 30), (2, 9)]), m, 2).orderBy("ticket_id").collect()]
    assert got == [True, False, False]
