from pyspark.sql import functions as F

from linefault.functions.columns import period_of
from linefault.functions.naming import feature_grid
from linefault.operators import clusters as K
from linefault.plans import base as Q
from linefault.plans.detector import FaultDetector, choose_feature_count
from linefault.sources import adapters as A


def test_fit_transform_faults(spark, sf):
    tel, net = A.telemetry(spark, sf), Q.net(spark, sf)
    detector = FaultDetector(("snr", "tx"), A.POINTS_PER_DAY, n_features=2, days=(1,), tenths=(5,), min_tickets=5, max_share=0.3)
    model = detector.fit(tel, net, A.PERIOD_END)
    rows = model.thresholds.collect()
    assert 1 <= len(rows) <= 2 and all(r.trr > 1 for r in rows)
    verdicts = model.transform(tel)
    assert {"fired", "abnormal"} <= set(verdicts.columns) and verdicts.count() == tel.count()
    assert model.faults(tel, 1, 2, A.PERIOD_END).count() >= model.faults(tel, 2, 2, A.PERIOD_END).count()
    swept = choose_feature_count(detector.scores(tel, net, A.PERIOD_END), tel, net, A.POINTS_PER_DAY, 2, 1, 2, A.PERIOD_END).collect()
    assert [r.n for r in swept] == list(range(1, len(swept) + 1))


def test_scoring_reads_only_the_selected_metrics(spark, sf):
    tel, net = A.telemetry(spark, sf), Q.net(spark, sf)
    model = FaultDetector(("snr",), A.POINTS_PER_DAY, n_features=1, days=(1,), tenths=(), min_tickets=5, max_share=0.3).fit(tel, net, A.PERIOD_END)
    plan = model.transform(tel).select("rec_id", "abnormal")._jdf.queryExecution().optimizedPlan().toString()
    assert "AS rx" not in plan and "AS unerrored" not in plan


def test_typer(spark, sf):
    """Types of the periods that the detector finds, against the plant that it never sees."""
    d = sf.replace("0.001", "0.01")
    typed = Q.types(spark, d)
    assert typed.count() == Q.periods(spark, d).count()
    slot = period_of("ts", Q.START, Q.typer().period_hours).alias("slot")
    truth = A.telemetry(spark, d).groupBy("device", slot).agg(F.max("maint").alias("shared"), F.max("serv").alias("lone"))
    found = {(r.shared, r.fault_type): r["count"] for r in typed.join(truth.where("shared or lone"), ["device", "slot"]).groupBy("shared", "fault_type").count().collect()}
    right = lambda shared, kind: found.get((shared, kind), 0) / max(1, sum(n for (s, _), n in found.items() if s == shared))
    assert right(True, "maintenance") > right(False, "maintenance")


def test_ratio_counts_only_diagnosed_periods(spark):
    typed = spark.createDataFrame([(1, 0, 0.5, "maintenance"), (2, 0, 0.5, "service")], "device long, slot int, cut double, fault_type string")
    counted = spark.createDataFrame([(1, 0, 2, 4.0), (1, 1, 9, 9.0), (2, 0, 1, 8.0), (3, 0, 5, 5.0)], "device long, slot int, tickets long, hours double")
    r = K.maintenance_ratio(typed, counted).first()
    assert (r.k_mm, r.h_m, r.k_ms, r.h_s, r.trr_m) == (2, 4.0, 1, 8.0, 4.0)


def test_registered_search_covers_the_whole_grid():
    detector = Q.detector()
    assert len(feature_grid(detector.metrics, detector.days, detector.tenths)) == 37 * len(A.METRICS) == 333
    assert tuple(Q.typer().metrics) == ("snr", "tx")


def test_no_features_no_faults(spark, sf):
    """Too few tickets for any guard: an empty model marks nothing."""
    model = FaultDetector(("snr",), A.POINTS_PER_DAY, days=(1,), tenths=(), min_tickets=10**6).fit(A.telemetry(spark, sf), Q.net(spark, sf), A.PERIOD_END)
    assert model.features() == [] and model.transform(A.telemetry(spark, sf)).where("abnormal").count() == 0


def test_empty_tables(spark, sf):
    tel, net = A.telemetry(spark, sf).where("false"), Q.net(spark, sf).where("false")
    model = FaultDetector(A.METRICS, A.POINTS_PER_DAY).fit(tel, net, A.PERIOD_END)
    assert model.features() == [] and model.faults(tel, 1, 2, A.PERIOD_END).count() == 0
