import pytest

from linefault.functions import udfs
from linefault.sources import adapters as A
from linefault.sources.replay import ReplaySource


def test_sql_functions(spark):
    udfs.register(spark)
    assert spark.sql("SELECT ewma_last(array(1D, 2D, 3D), 0.5D)").first()[0] == 2.25
    assert [tuple(r) for r in spark.sql("SELECT * FROM faults_of(array(false, false, true, true, false, true, true, true, false, false), 2, 3)").collect()] == [(3, 8, 3)]
    assert spark.sql("SELECT signal_ratio_db(100, 1), signal_ratio_db(1, 0)").first() == (20.0, None)


def test_replay(spark, sf, tmp_path):
    A.telemetry(spark, sf).write.parquet(f"{tmp_path}/tel")
    spark.dataSource.register(ReplaySource)
    batch = spark.read.format("replay").option("path", f"{tmp_path}/tel").load()
    assert batch.count() == 799 and batch.rdd.getNumPartitions() == 2
    stream = spark.readStream.format("replay").option("path", f"{tmp_path}/tel").load()
    query = stream.writeStream.format("memory").queryName("replayed").option("checkpointLocation", f"{tmp_path}/check").trigger(processingTime="0 seconds").start()
    try:
        for _ in range(60):
            if spark.table("replayed").count() == 799:
                break
            query.awaitTermination(0.5)
        assert spark.table("replayed").count() == 799
    finally:
        query.stop()


def test_windowed_rates_and_sessions(spark, sf, tmp_path):
    from linefault.sources.readers import TELEMETRY, stream_records
    from linefault.streaming.monitor import fault_sessions, windowed_rates
    from pyspark.sql import functions as F

    A.telemetry(spark, sf).select([f.name for f in TELEMETRY.fields]).coalesce(1).write.parquet(f"{tmp_path}/tel")
    rows = stream_records(spark, f"{tmp_path}/tel", TELEMETRY).withColumn("abnormal", F.col("snr") < 29)
    for name, out in (("rates", windowed_rates(rows)), ("sessions", fault_sessions(rows.withColumn("marked", F.col("abnormal")).withColumn("hits", F.lit(1))))):
        out.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", f"{tmp_path}/{name}").trigger(availableNow=True).start().awaitTermination()
    batch = A.telemetry(spark, sf).groupBy("node", F.to_date("ts").alias("day")).count().where("day < '2024-01-28'").count()
    assert spark.table("rates").where("start < '2024-01-28'").count() == batch
    assert spark.table("sessions").count() > 5


def test_stream_join(spark):
    pytest.importorskip("pyspark")
    from linefault.streaming.monitor import tickets_after_dispatch

    rates = spark.readStream.format("rate").load()
    d = rates.selectExpr("value AS device", "timestamp AS ts", "true AS dispatch")
    t = rates.selectExpr("value AS ticket_id", "value AS account", "timestamp AS created")
    assert tickets_after_dispatch(d, t).isStreaming
