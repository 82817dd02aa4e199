import glob
import shutil
import tempfile

from pyspark.sql import functions as F

from linefault.operators.selection import mark_windows
from linefault.plans.detector import DetectorModel
from linefault.sources import adapters as A
from linefault.sources.readers import MODEL, TELEMETRY, load_model, read_records, save_model, stream_records
from linefault.streaming.monitor import monitor

RULES = [("snr-avg-1", "snr", "avg", 1, "below", 30.0, None, 2.0), ("snr-ewma-5", "snr", "ewma", 5, "below", 31.0, None, 1.5), ("tx-wma-diff-1", "tx", "wma-diff", 1, "above", None, 3.0, 1.2)]


def test_stream_equals_batch(spark, sf):
    folder = tempfile.mkdtemp()
    try:
        tel = A.telemetry(spark, sf).select([f.name for f in TELEMETRY.fields])
        rows = tel.orderBy("ts").collect()
        for i in range(0, len(rows), 200):  # in time order, one file after another
            spark.createDataFrame(rows[i : i + 200], TELEMETRY).coalesce(1).write.mode("append").parquet(f"{folder}/in")
        model = spark.createDataFrame([(*r, 0, 0.0, 0, 0.0) for r in RULES], MODEL)
        save_model(model, f"{folder}/model")
        model = load_model(spark, f"{folder}/model")
        want = mark_windows(DetectorModel(model, A.POINTS_PER_DAY).transform(tel), 2, 4)
        thresholds = [r.asDict() for r in model.collect()]
        query = monitor(stream_records(spark, f"{folder}/in", TELEMETRY), thresholds, 2, 4, A.POINTS_PER_DAY).writeStream.format("memory").queryName("monitored").option("checkpointLocation", f"{folder}/check").trigger(availableNow=True).start()
        query.awaitTermination()
        got = {r.rec_id: (r.abnormal, r.hits, r.marked) for r in spark.table("monitored").collect()}
        expect = {r.rec_id: (r.abnormal, r.hits, r.marked) for r in want.collect()}
        assert len(glob.glob(f"{folder}/in/*.parquet")) == 4
        assert got == expect
        assert 0 < sum(x[2] for x in got.values()) < len(got)
    finally:
        shutil.rmtree(folder)


def test_formats(spark, sf):
    folder = tempfile.mkdtemp()
    try:
        tel = A.telemetry(spark, sf).select([f.name for f in TELEMETRY.fields])
        for form in ("parquet", "json", "csv", "orc"):
            tel.write.option("header", True).format(form).save(f"{folder}/{form}")
            assert read_records(spark, f"{folder}/{form}", TELEMETRY, form).agg(F.round(F.sum("snr"), 6), F.count("ts")).first() == tel.agg(F.round(F.sum("snr"), 6), F.count("ts")).first()
    finally:
        shutil.rmtree(folder)
