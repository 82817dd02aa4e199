"""Shared pieces of the training-data operators: shared-folder staging, text keys and bounded sizes."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
ASCII_SPACE = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (spark.checkpoint.dir of the session).

    Only a local master may fall back to a temporary folder of its own; on a cluster an
    unset folder is an error, because executors would not see the driver's files.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    own = getattr(shared_dir, "own", None)
    if own is None:
        own = shared_dir.own = "file://" + tempfile.mkdtemp(prefix="linefault-")
    return own


#: Rows of one Arrow batch between the JVM and Python: whole texts travel, so batches must be few rows.
ARROW_ROWS = 500


def small_batches(spark: SparkSession) -> None:
    """Bound what one Arrow batch of texts takes in both processes, for this session's Python stages."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", ARROW_ROWS)


def staged(df: DataFrame, label: str) -> DataFrame:
    """Write df once to the shared folder as Parquet and read it back.

    This cuts lineage with a real table, so a lost executor costs a file read and not the
    recomputation of everything before. The folder is removed when the driver's JVM ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/linefault-stage/{uuid.uuid4().hex}/{label}"
    df.write.parquet(path)
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(target)
    return spark.read.schema(df.schema).parquet(path)


#: Keys that hold more than one in so many rows are joined by broadcast; there are fewer of them than this.
HEAVY = 1000


def join_by_weight(rows: DataFrame, keyed: DataFrame, on: list[str], weight: str, total: int) -> DataFrame:
    """rows joined with keyed, which has one row per key and in `weight` how many of `rows` have it.

    The weights add up to `total` at most, so fewer than HEAVY keys weigh more than total / HEAVY: these are
    broadcast, and a key with a third of all rows never meets in one task. The others are joined by shuffle.
    """
    heavy = F.broadcast(keyed.where(F.col(weight) * HEAVY > F.lit(total)))
    light = keyed.where(F.col(weight) * HEAVY <= F.lit(total))
    rest = rows.join(heavy.select(*on), on, "left_anti").join(light, on)
    return rows.join(heavy, on).unionByName(rest)


def ascii_lower(col: Column) -> Column:
    """Lower-case A-Z alone; every other code point stays as it is."""
    return F.translate(col, UPPER, UPPER.lower())


def fresh(name: str, taken: list[str]) -> str:
    """A column name that no input column has (names compare without case, as Spark does)."""
    have = {c.lower() for c in taken}
    while name.lower() in have:
        name = "_" + name
    return name


def columns_of(df: DataFrame) -> list[Column]:
    """All columns of df by quoted name, so that names with dots work as well."""
    return [F.col(f"`{c}`") for c in df.columns]


def power_of_two(n: float, least: int, most: int) -> int:
    size = least
    while size < n and size < most:
        size *= 2
    return size
