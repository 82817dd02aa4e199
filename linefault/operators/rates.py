"""Held intervals, tickets in force, and ticketing rates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import hours_between, ratio
from ..sources.staging import staged

KEYS, ORDER = ("device",), ("ts", "rec_id")


def held_intervals(df: DataFrame, period_end: str, max_gap_hours: float | None = None, hold: str = "forward", keys=KEYS, order=ORDER) -> DataFrame:
    """df with start, end and hours: how long each record's value is taken to last.

    forward: until the next record, the last one until period_end. backward: since the record before, the first
    one for no time. max_gap_hours caps what one record can stand for.
    """
    along = Window.partitionBy(*keys).orderBy(*order)
    close = F.lit(period_end).cast("timestamp_ntz")
    if hold == "forward":
        start, end = F.col("ts"), F.coalesce(F.lead("ts").over(along), close)
    elif hold == "backward":
        start, end = F.coalesce(F.lag("ts").over(along), F.col("ts")), F.col("ts")
    else:
        raise ValueError("hold is forward or backward")
    timed = df.withColumn("start", start).withColumn("end", end)
    hours = F.greatest(hours_between("start", "end"), F.lit(0.0))
    return timed.withColumn("hours", hours if max_gap_hours is None else F.least(hours, F.lit(float(max_gap_hours))))


def tickets_in_force(df: DataFrame, tickets: DataFrame, hold: str = "forward", tie: str = "rec_id") -> DataFrame:
    """(ticket columns, rec_id): the record in force when a ticket was created, null if none is.

    An as-of join by sorting both sides together per account; linear, and immune to many tickets per record.
    Of records of one time the last by the tie column counts (forward), or the first (backward).
    """
    records = df.select(F.col("account").alias("a"), F.col("ts").alias("t"), F.col(tie).alias("o"), F.lit(0 if hold == "forward" else 2).alias("kind"), F.col("rec_id").alias("r"), F.lit(None).cast(tickets.schema).alias("ticket"))
    asked = tickets.select(F.col("account").alias("a"), F.col("created").alias("t"), F.lit(None).cast(dict(df.dtypes)[tie]).alias("o"), F.lit(1).alias("kind"), F.lit(None).cast(dict(df.dtypes)["rec_id"]).alias("r"), F.struct(*tickets.columns).alias("ticket"))
    along = Window.partitionBy("a").orderBy("t", "kind", "o")
    if hold == "forward":
        found = F.last("r", ignorenulls=True).over(along.rowsBetween(Window.unboundedPreceding, 0))
    else:
        found = F.first("r", ignorenulls=True).over(along.rowsBetween(0, Window.unboundedFollowing))
    return records.unionByName(asked).withColumn("found", found).where("kind = 1").select("ticket.*", F.col("found").alias("rec_id"))


def count_tickets(intervals: DataFrame, tickets: DataFrame, hold: str = "forward", name: str = "tickets", tie: str = "rec_id") -> DataFrame:
    """intervals with the number of tickets that fall in each record's interval."""
    joined = tickets_in_force(intervals, tickets, hold, tie)
    counts = joined.where("rec_id is not null").groupBy("rec_id").agg(F.count(F.lit(1)).alias(name))
    return intervals.join(counts, "rec_id", "left").withColumn(name, F.coalesce(name, F.lit(0)).cast("long"))


def ticket_rate(counted: DataFrame, where: Column | None = None) -> DataFrame:
    """(tickets, hours, rate) over the records that the condition selects."""
    rows = counted if where is None else counted.where(where)
    return rows.agg(F.sum("tickets").alias("tickets"), F.sum("hours").alias("hours")).withColumn("rate", ratio(F.col("tickets"), F.col("hours")))


def split_rates(predicate: Column, tickets: str = "tickets", hours: str = "hours") -> list[Column]:
    """Aggregates k_abn, h_abn, k_norm, h_norm of a predicate; rows where it is null count on neither side."""
    side = lambda cond, col: F.coalesce(F.sum(F.when(cond, F.col(col))), F.lit(0))
    return [side(predicate, tickets).alias("k_abn"), side(predicate, hours).cast("double").alias("h_abn"), side(~predicate, tickets).alias("k_norm"), side(~predicate, hours).cast("double").alias("h_norm")]


def rate_ratio(k_abn: Column, h_abn: Column, k_norm: Column, h_norm: Column) -> Column:
    """Ticketing rate in abnormal time over that in normal time; null where either is undefined or zero below."""
    return F.try_divide(ratio(k_abn, h_abn), ratio(k_norm, h_norm))


def trr(counted: DataFrame, predicate: Column) -> DataFrame:
    """One row: the four sums and trr."""
    return counted.agg(*split_rates(predicate)).withColumn("trr", rate_ratio(*[F.col(c) for c in ("k_abn", "h_abn", "k_norm", "h_norm")]))


def _adjacent(values: DataFrame) -> DataFrame:
    """values (lo, ...) with bin, their rank, and hi, the next value. Dealt by range and ranked within each part; a part needs
    of the others only how many values come before and the first one after, which is one row a part."""
    dealt = staged(values.repartitionByRange("lo").sortWithinPartitions("lo").withColumn("part", F.spark_partition_id()), "by_value")
    along = Window.orderBy("part")
    parts = dealt.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.min("lo").alias("least"))
    known = parts.select("part", F.coalesce(F.sum("n").over(along.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"), F.lead("least").over(along).alias("following"))
    inside = Window.partitionBy("part").orderBy("lo")
    ranked = dealt.join(F.broadcast(known), "part")
    return ranked.withColumn("hi", F.coalesce(F.lead("lo").over(inside), F.col("following"))).withColumn("bin", (F.row_number().over(inside) + F.col("before")).cast("int")).drop("part", "before", "following")


def rate_curve(counted: DataFrame, metric: str, bins: int | None = None, exact_edges: bool = False) -> DataFrame:
    """(bin, lo, hi, tickets, hours, rate, rate_over_base) along a metric, rate_over_base in units of the overall rate.

    Without bins every pair of adjacent distinct values is a bin, exactly, over values dealt by range. With bins they carry
    about equal mass: edges by approx_percentile, or with exact_edges by exact percentiles.
    """
    rows = counted.where(F.col(metric).isNotNull())
    if bins is None:
        cut = _adjacent(rows.groupBy(F.col(metric).alias("lo")).agg(F.sum("tickets").alias("tickets"), F.sum("hours").alias("hours")))
    else:
        marks = [i / bins for i in range(1, bins)]
        at = F.percentile(metric, F.array(*[F.lit(m) for m in marks])) if exact_edges else F.percentile_approx(metric, F.lit(marks), 10_000)
        edges = rows.agg(F.array_distinct(at).alias("edges")).scalar()
        placed = rows.withColumn("edges", edges).withColumn("bin", F.size(F.filter("edges", lambda e: e <= F.col(metric))) + 1)
        cut = placed.groupBy("bin").agg(F.min(metric).alias("lo"), F.max(metric).alias("hi"), F.sum("tickets").alias("tickets"), F.sum("hours").alias("hours"))
    base = rows.agg(ratio(F.sum("tickets"), F.sum("hours")).alias("base")).scalar()
    rated = cut.withColumn("rate", ratio(F.col("tickets"), F.col("hours")))
    return rated.select("bin", "lo", "hi", "tickets", "hours", "rate", F.try_divide("rate", base).alias("rate_over_base"))
