"""Views of the given tables in canonical shape: planted telemetry and tickets, long series, device vectors, ticket text.

The tables carry no signal of their own. The planted view shifts two metrics inside known fault
periods, so that methods can be compared with a truth; plant=False gives the untouched control.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.columns import add_hours, tap_ratio_db
from .readers import read_table

PERIOD_START, PERIOD_END = "2024-01-01", "2024-01-31"
POINTS_PER_DAY = 2
METRICS = ("snr", "tx", "rx", "unerrored", "corrected", "uncorrectable", "t3", "t4", "tap")


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = read_table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("account"), F.col("c_nationkey").cast("int").alias("node"))
    events = read_table(spark, sf_dir, "events").select("event_id", "ts", F.col("user_id").alias("account"), "event_type", "value", F.get_json_object("props", "$.k").cast("int").alias("k"))
    start = F.lit(PERIOD_START).cast("timestamp_ntz")
    day = F.timestamp_diff("MICROSECOND", start, F.col("ts")) / F.lit(86_400_000_000.0)
    return events.join(customers, "account").withColumn("day", day)


def _within(day: Column, start: Column) -> Column:
    return (day >= start) & (day < start + 3)


def planted(account: Column, node: Column, day: Column) -> tuple[Column, Column]:
    """(shared fault, single-home fault) of an account at a day."""
    shared = (node % 5 == 0) & (_within(day, 3 + node % 11) | _within(day, 19 + node % 8))
    single = (account % 4 == 1) & (node % 5 != 0) & (_within(day, 2 + (7 * account) % 13) | _within(day, 19 + (5 * account) % 7))
    return shared, single


def telemetry(spark: SparkSession, sf_dir: str, plant: bool = True) -> DataFrame:
    """One row per poll: rec_id, ts, device, account, node, nine metrics, and the planted truth."""
    base = _events(spark, sf_dir).where("event_type <> 'error'")
    shared, single = planted(F.col("account"), F.col("node"), F.col("day"))
    k, v = F.col("k"), F.col("value")
    drop = (lambda a, b: F.when(F.col("maint"), F.lit(a)).when(F.col("serv"), F.lit(b)).otherwise(0.0)) if plant else lambda a, b: F.lit(0.0)
    named = base.withColumn("maint", shared).withColumn("serv", single)
    return named.select(
        F.col("event_id").alias("rec_id"), "ts", F.col("account").alias("device"), "account", "node", "day",
        (36 - v / 25 - drop(9.0, 7.0)).alias("snr"), (45 + k / 50 + drop(6.0, 5.0)).alias("tx"), (-5 + (k - 50) / 25).alias("rx"), (10 * v).alias("unerrored"),
        k.cast("double").alias("corrected"), (k % 7).cast("double").alias("uncorrectable"), (k % 5).cast("double").alias("t3"), (k % 3).cast("double").alias("t4"), (18 + k / 10).alias("tap"), "maint", "serv",
    )


def tickets(spark: SparkSession, sf_dir: str, plant: bool = True) -> DataFrame:
    base = _events(spark, sf_dir).where("event_type = 'error'")
    shared, single = planted(F.col("account"), F.col("node"), F.col("day"))
    k = F.col("k")
    named = base.withColumn("maint", shared if plant else F.lit(False)).withColumn("serv", single if plant else F.lit(False)).withColumn("is_network", F.col("maint") | F.col("serv") | (k >= 85))
    words = F.when(k % 3 == 0, "Data Down").when(k % 3 == 1, "Noisy Line").otherwise("Slow Speed")
    return named.select(
        F.col("event_id").alias("ticket_id"), "account", "node", F.col("ts").alias("created"), F.when(k % 20 != 0, add_hours("ts", F.col("value"))).alias("closed"), "day",
        F.when(F.col("is_network"), "Dispatch").when(k < 45, "Education").otherwise("Cancelled").alias("action"), F.when(F.col("is_network"), words).otherwise("Billing").alias("description"),
        "is_network", F.col("maint").alias("is_maintenance"), F.when(F.col("maint"), 1000 * F.col("node").cast("long") + F.floor("day")).alias("primary_id"),
    )


SUPPLY_END = "2001-12-31"
SUPPLY_ORDER = ("ts", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice")


def supply_telemetry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Long series with many ties: one per supplier, about 400 points each. rec_id follows the order of the series."""
    nodes = read_table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("device"), F.col("s_nationkey").cast("int").alias("node"))
    rows = read_table(spark, sf_dir, "lineitem").where("l_returnflag <> 'R'").withColumn("ts", F.col("l_shipdate"))
    place = F.row_number().over(Window.partitionBy("device").orderBy(*SUPPLY_ORDER))
    joined = rows.join(nodes, rows.l_suppkey == nodes.device).withColumn("rec_id", F.col("device") * F.lit(10**9) + place)
    return joined.select("rec_id", "device", F.col("device").alias("account"), "node", "ts", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice", "l_quantity", "l_discount", "l_tax")


def supply_tickets(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'")
    orders = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority", "o_orderstatus")
    joined = rows.join(orders, rows.l_orderkey == orders.o_orderkey)
    return joined.select(F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice").alias("ticket_id"), F.col("l_suppkey").alias("account"), F.col("l_shipdate").alias("created"), add_hours("l_shipdate", F.col("l_quantity")).alias("closed"), F.col("o_orderpriority").alias("severity"), F.col("o_orderstatus").alias("status"))


def vectors(spark: SparkSession, sf_dir: str, alpha: float = 0.0, nodes: int = 1) -> DataFrame:
    """(node, slot, device, vector, label): embeddings with alpha added on their label's coordinate, renormalised."""
    emb = read_table(spark, sf_dir, "embeddings")
    moved = F.transform("embedding", lambda v, i: v.cast("double") + F.when(i == F.col("label"), F.lit(float(alpha))).otherwise(0.0))
    norm = F.sqrt(F.aggregate("moved", F.lit(0.0), lambda acc, v: acc + v * v))
    return emb.withColumn("moved", moved).withColumn("norm", norm).select((F.col("vec_id") % nodes).cast("int").alias("node"), F.lit(0).alias("slot"), F.col("vec_id").alias("device"), F.transform("moved", lambda v: v / F.col("norm")).alias("vector"), "label")


def grouped_vectors(spark: SparkSession, sf_dir: str, alpha: float, groups: int = 16, nodes: int = 4) -> DataFrame:
    """(node, slot, device, vector, label): the shape of a labelled set of some shared faults and some lone ones.

    One device in seven (113 of 813) is alone, its own label; the others belong to one of the groups, each inside one node,
    and have alpha added on their group's coordinate.
    """
    emb = read_table(spark, sf_dir, "embeddings")
    group = F.when(F.col("vec_id") % 7 != 3, F.col("vec_id") % groups)
    moved = F.transform("embedding", lambda v, i: v.cast("double") + F.when(i == F.col("fault"), F.lit(float(alpha))).otherwise(0.0))
    label = F.coalesce(F.col("fault"), F.col("vec_id") + groups)
    return emb.withColumn("fault", group).select((F.col("vec_id") % groups % nodes).cast("int").alias("node"), F.lit(0).alias("slot"), F.col("vec_id").alias("device"), moved.alias("vector"), label.alias("label"))


def tap_vectors(spark: SparkSession, sf_dir: str, main: int = 8) -> DataFrame:
    """(device, day, tap_db) of equalisers in health and out of it: the main tap is 9.5 to 24.5 dB above all others, by device."""
    emb = read_table(spark, sf_dir, "embeddings")
    energy = F.aggregate("embedding", F.lit(0.0), lambda acc, v: acc + v.cast("double") * v.cast("double"))
    own = F.aggregate(F.slice("embedding", 2 * main + 1, 2), F.lit(0.0), lambda acc, v: acc + v.cast("double") * v.cast("double"))
    level = F.sqrt((energy - own) * F.pow(F.lit(10.0), (F.lit(9.5) + F.col("vec_id") % 16) / 10))
    taps_ = F.transform("embedding", lambda v, i: F.when(i == 2 * main, level).when(i == 2 * main + 1, F.lit(0.0)).otherwise(v.cast("double")))
    return emb.select(F.col("vec_id").alias("device"), (F.col("vec_id") % 5).cast("int").alias("day"), tap_ratio_db(taps_, main).alias("tap_db"))


def taps(spark: SparkSession, sf_dir: str, main: int = 8) -> DataFrame:
    """(device, day, tap_db): embeddings read as equaliser taps, sampled on five days."""
    return read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("device"), (F.col("vec_id") % 5).cast("int").alias("day"), tap_ratio_db("embedding", main).alias("tap_db"))


def text_tickets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One free-text ticket per conversation: all its user turns in order."""
    turns = read_table(spark, sf_dir, "conversations").where("role = 'user'")
    told = turns.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "text"))).alias("told"))
    return told.select(F.col("conv_id").alias("ticket_id"), F.concat_ws("\n", F.col("told.text")).alias("description"))


def document_tickets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents read as ticket texts."""
    return read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("ticket_id"), F.col("text").alias("description"))
