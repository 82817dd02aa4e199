"""Tables that cut lineage: written once as Parquet in the folder that all executors share, and read back."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session. Only a local master may fall back to a temporary folder of its own; on a
    cluster an unset folder is an error, because executors would not see the driver's files."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    own = getattr(shared_dir, "own", None)
    if own is None:
        own = shared_dir.own = "file://" + tempfile.mkdtemp(prefix="linefault-")
    return own


def staged(df: DataFrame, label: str) -> DataFrame:
    """df, computed once. A lost executor then costs a file read and not all that came before; the folder goes when the
    driver's JVM ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/linefault-stage/{uuid.uuid4().hex}/{label}"
    df.write.parquet(path)
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(target)
    return spark.read.schema(df.schema).parquet(path)
