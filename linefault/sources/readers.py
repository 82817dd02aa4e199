"""Reading and writing: tables, telemetry files with fixed schemas, streams and learned models."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TELEMETRY = T.StructType(
    [T.StructField("rec_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("device", T.LongType()), T.StructField("account", T.LongType()), T.StructField("node", T.IntegerType())]
    + [T.StructField(m, T.DoubleType()) for m in ("snr", "tx", "rx", "unerrored", "corrected", "uncorrectable", "t3", "t4", "tap")]
)
TICKETS = T.StructType(
    [T.StructField("ticket_id", T.LongType()), T.StructField("account", T.LongType()), T.StructField("created", T.TimestampNTZType()), T.StructField("closed", T.TimestampNTZType())]
    + [T.StructField(c, T.StringType()) for c in ("action", "description")]
    + [T.StructField(c, T.BooleanType()) for c in ("is_network", "is_maintenance")]
    + [T.StructField("primary_id", T.LongType())]
)
FORMATS = ("parquet", "orc", "csv", "json")


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_records(spark: SparkSession, path: str, schema: T.StructType, form: str = "parquet") -> DataFrame:
    """Files of records with a declared schema; CSV needs a header line. Nothing is inferred."""
    if form not in FORMATS:
        raise ValueError(f"unknown format {form}")
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if form == "csv" else reader).format(form).load(path)


def stream_records(spark: SparkSession, path: str, schema: T.StructType, form: str = "parquet", files_per_trigger: int = 1) -> DataFrame:
    """The same files as a stream, with ts as TIMESTAMP, since watermarks reject TIMESTAMP_NTZ."""
    rows = spark.readStream.schema(schema).format(form).option("maxFilesPerTrigger", files_per_trigger).load(path)
    stamps = {f.name: F.col(f.name).cast("timestamp") for f in schema.fields if isinstance(f.dataType, T.TimestampNTZType)}
    return rows.withColumns(stamps) if stamps else rows


def write_by_day(df: DataFrame, path: str, ts: str = "ts", cluster: str = "device", form: str = "parquet", mode: str = "error") -> None:
    """Records partitioned by day and clustered by device, so a period reads only its days and row groups prune by device."""
    df.withColumn("day", F.to_date(ts)).repartition("day").sortWithinPartitions("day", cluster, ts).write.partitionBy("day").format(form).mode(mode).save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, key: str = "device", order: str = "ts", mode: str = "error") -> None:
    """A table bucketed and sorted by series, so windows and joins over series need no exchange."""
    df.write.bucketBy(buckets, key).sortBy(key, order).mode(mode).saveAsTable(name)


def save_model(thresholds: DataFrame, path: str, form: str = "json") -> None:
    """The learned thresholds, a few rows, as one file."""
    thresholds.coalesce(1).write.mode("overwrite").format(form).save(path)


MODEL = "feature string, metric string, model string, param int, direction string, low double, high double, trr double, k_abn long, h_abn double, k_norm long, h_norm double"


def load_model(spark: SparkSession, path: str, form: str = "json") -> DataFrame:
    return spark.read.schema(MODEL).format(form).load(path)
