"""Faults from marks, their merging, tickets inside them, dispatches and call diagnosis."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import hours_between, period_of

KEYS, ORDER = ("device",), ("ts", "rec_id")


def fault_events(marks: DataFrame, period_end: str, y: int = 1, extent: str = "onset", keys=KEYS, order=ORDER) -> DataFrame:
    """(device, account, node, fault_no, onset, end, hours, points, peak, open), one row per run of marked records.

    A fault ends where the first unmarked record after it starts, or with the period if none comes. extent='span' reaches
    back to the first record of the window that set the fault off. marks needs start and end of the records.
    """
    along = Window.partitionBy(*keys).orderBy(*order)
    before = F.coalesce(F.lag("marked").over(along), F.lit(False))
    opened = F.col("marked") & ~before
    oldest = F.first("start").over(along.rowsBetween(1 - y, 0))
    held = marks.withColumn("opened", opened.cast("int")).withColumn("next_start", F.lead("start").over(along)).withColumn("oldest", oldest)
    numbered = held.withColumn("fault_no", F.sum("opened").over(along.rowsBetween(Window.unboundedPreceding, 0))).where("marked")
    onset = F.min("start") if extent == "onset" else F.min(F.when(F.col("opened") == 1, F.col("oldest")))
    close = F.lit(period_end).cast("timestamp_ntz")
    out = numbered.groupBy(*keys, "fault_no").agg(F.first("account").alias("account"), F.first("node").alias("node"), onset.alias("onset"), F.max(F.coalesce("next_start", close)).alias("end"), F.count(F.lit(1)).alias("points"), F.max("hits").alias("peak"), F.max(F.col("next_start").isNull()).alias("open"))
    return out.withColumn("hours", hours_between("onset", "end"))


def _joined(spans: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Spans (onset, end, faults, accounts) that overlap within the keys as one, numbered in order."""
    along = Window.partitionBy(*keys).orderBy("onset", "end", "first")
    reach = F.max("end").over(along.rowsBetween(Window.unboundedPreceding, -1))
    starts = spans.withColumn("new", (reach.isNull() | (F.col("onset") >= reach)).cast("int"))
    numbered = starts.withColumn("event_no", F.sum("new").over(along.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(*keys, "event_no").agg(F.min("onset").alias("onset"), F.max("end").alias("end"), F.sum("faults").alias("faults"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("accounts")))).alias("accounts"), F.min("first").alias("first"))


def merge_simultaneous(faults: DataFrame, scope: str = "node") -> DataFrame:
    """Faults that overlap within the scope as one: (scope key, event_no, onset, end, hours, faults, accounts).

    scope: 'device' (nothing merges across devices), 'node' or 'all'. With 'all', faults are first merged within the day
    of their onset, so that one task sees the days' events and not every fault.
    """
    key = {"device": F.col("device").cast("string"), "node": F.col("node").cast("string"), "all": F.lit("all")}[scope]
    spans = faults.select(key.alias("scope"), "onset", "end", F.lit(1).cast("long").alias("faults"), F.array("account").alias("accounts"), F.struct("device", "fault_no").alias("first"))
    if scope == "all":
        spans = _joined(spans.withColumn("day", F.to_date("onset")), ["scope", "day"]).drop("day", "event_no")
    return _joined(spans, ["scope"]).drop("first").withColumn("hours", hours_between("onset", "end"))


def tickets_in_faults(faults: DataFrame, tickets: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """(ticket_id, account, created, device, fault_no, onset, end, and `by` of the fault): onset <= created < end, same account.

    A range join on day buckets: faults are spread over the days they touch, tickets have one day, and the
    exact bounds are the residual condition; never a nested loop.
    """
    days = F.sequence(F.to_date("onset"), F.to_date("end"))
    spread = faults.select("account", "device", "fault_no", "onset", "end", *by, F.explode(days).alias("day"))
    dated = tickets.select("ticket_id", F.col("account"), "created", F.to_date("created").alias("day"))
    met = dated.join(spread, ["account", "day"]).where((F.col("created") >= F.col("onset")) & (F.col("created") < F.col("end")))
    return met.select("ticket_id", "account", "created", "device", "fault_no", "onset", "end", *by)


def dispatch_decisions(faults: DataFrame, types: DataFrame | None = None, start: str = "", period_hours: int = 0) -> DataFrame:
    """(device, account, node, at, technician): send somebody when a fault sets in, of the kind its type asks for.

    types: (device, slot, fault_type), one type for each device and period of period_hours from start; a device without a type
    in the period of the onset gets anyone.
    """
    sent = faults.select("device", "account", "node", "fault_no", F.col("onset").alias("at"))
    if types is None:
        return sent.withColumn("technician", F.lit("any"))
    kinds = types.select("device", "slot", F.col("fault_type").alias("technician"))
    placed = sent.withColumn("slot", period_of("at", start, period_hours)).join(kinds, ["device", "slot"], "left")
    return placed.drop("slot").withColumn("technician", F.coalesce("technician", F.lit("any")))


def diagnose_calls(calls: DataFrame, marks: DataFrame, x: int, tie: str = "rec_id", types: DataFrame | None = None, start: str = "", period_hours: int = 0) -> DataFrame:
    """calls with hits and network_cause: whether at least x of the records before the call were abnormal. With types (as in
    dispatch_decisions) also fault_type, that of the device in the period of the record in force; null without a network cause.

    marks carries hits of the window; a call without any earlier record has null hits and no network cause.
    """
    from .rates import tickets_in_force

    seen = marks.select("rec_id", "hits") if types is None else marks.select("rec_id", "hits", "device", period_of("ts", start, period_hours).alias("slot"))
    placed = tickets_in_force(marks, calls, tie=tie).join(seen, "rec_id", "left")
    judged = placed.withColumn("network_cause", F.coalesce(F.col("hits") >= x, F.lit(False)))
    if types is None:
        return judged
    named = judged.join(types.select("device", "slot", "fault_type"), ["device", "slot"], "left")
    return named.drop("device", "slot").withColumn("fault_type", F.when(F.col("network_cause"), F.col("fault_type")))
