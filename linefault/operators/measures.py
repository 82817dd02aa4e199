"""Accuracy, coverage and rate measures of faults, overlap of two detections, and cluster agreement."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import hours_between, ratio
from ..sources.staging import staged
from .faults import fault_events, merge_simultaneous, tickets_in_faults
from .rates import count_tickets


def fault_scores(faults: DataFrame, tickets: DataFrame, intervals: DataFrame, scope: str = "device") -> DataFrame:
    """One row: faults, true_faults, accuracy, detected, tickets, coverage, ntr. tickets are the network-related ones.

    ntr is the rate of tickets in faulty time over the rate in all of the intervals' time; a ticket before its account's
    first record belongs to no time, so it counts in coverage alone, and the rate of all time is 1.
    """
    met = tickets_in_faults(faults, tickets)
    if scope == "device":
        true = met.select("device", "fault_no").distinct().agg(F.count(F.lit(1)).alias("true_faults"))
        total = faults.agg(F.count(F.lit(1)).alias("faults"))
    else:
        events = merge_simultaneous(faults, scope)
        members = events.select("scope", "event_no", "onset", "end", F.explode("accounts").alias("account")).withColumnRenamed("event_no", "fault_no").withColumn("device", F.col("scope"))
        true = tickets_in_faults(members, tickets).select("device", "fault_no").distinct().agg(F.count(F.lit(1)).alias("true_faults"))
        total = events.agg(F.count(F.lit(1)).alias("faults"))
    seen = met.agg(F.countDistinct("ticket_id").alias("detected"))
    every = tickets.agg(F.count(F.lit(1)).alias("tickets"))
    faulty = faults.agg(F.coalesce(F.sum("hours"), F.lit(0.0)).alias("fault_hours"))
    time = intervals.agg(F.sum("hours").alias("all_hours"))
    begun = intervals.groupBy("account").agg(F.min("start").alias("begun"))
    timed = tickets.select("account", "created").join(begun, "account").where("created >= begun").agg(F.count(F.lit(1)).alias("timed"))
    # Seven aggregates of one row each; as scalar subqueries they need no join.
    row = total.select("faults", *[df.scalar().alias(name) for df, name in ((true, "true_faults"), (seen, "detected"), (every, "tickets"), (faulty, "fault_hours"), (time, "all_hours"), (timed, "timed"))])
    rate = F.try_divide(ratio(F.col("detected"), F.col("fault_hours")), ratio(F.col("timed"), F.col("all_hours")))
    return row.select("faults", "true_faults", ratio(F.col("true_faults"), F.col("faults")).alias("accuracy"), "detected", "tickets", ratio(F.col("detected"), F.col("tickets")).alias("coverage"), rate.alias("ntr"))


def sweep_windows(verdicts: DataFrame, tickets: DataFrame, settings: Sequence[tuple[int, int]], period_end: str, scope: str = "device", keys=("device",), order=("ts", "rec_id")) -> DataFrame:
    """fault_scores of every (x, y), with x and y. verdicts has start, end and hours, and should be cached or staged."""
    from .selection import mark_windows

    out = None
    for x, y in settings:
        faults = fault_events(mark_windows(verdicts, x, y, keys=keys, order=order), period_end, y, keys=keys, order=order)
        row = fault_scores(faults, tickets, verdicts, scope).select(F.lit(x).alias("x"), F.lit(y).alias("y"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def fault_islands(counted: DataFrame, ys: Sequence[int], period_end: str, keys=("device",), order=("ts", "rec_id")) -> DataFrame:
    """(keys, account, node, y, x, onset, end, tickets, hours): the faults of every x in 0..y of all ys, in device scope.

    A window's count changes by one at most from record to record, so a record opens or closes no more than one fault a
    y: with running totals of tickets and hours a fault is the difference between its rise and the next fall at its level.
    So each record gives at most one row a y, and none where the count stays. x = 0 is one fault over all of a device's time.
    counted: records with start, tickets, hours and abnormal.
    """
    series = Window.partitionBy(*keys)
    along = series.orderBy(*order)
    past = along.rowsBetween(Window.unboundedPreceding, -1)
    flagged = F.coalesce(F.col("abnormal").cast("long"), F.lit(0))
    zero = lambda c: F.coalesce(c, F.lit(0))
    total = counted.withColumns({"seen": F.sum(flagged).over(along.rowsBetween(Window.unboundedPreceding, 0)), "before": zero(F.sum(flagged).over(past)), "k": zero(F.sum("tickets").over(past)), "h": F.coalesce(F.sum("hours").over(past), F.lit(0.0)), "k_all": F.sum("tickets").over(series), "h_all": F.sum("hours").over(series)})
    now = lambda y: F.col("seen") - zero(F.lag("seen", y).over(along))
    then = lambda y: F.col("before") - zero(F.lag("before", y).over(along))
    held = total.withColumn("counts", F.array(*[F.struct(F.lit(y).alias("y"), now(y).alias("now"), then(y).alias("was")) for y in ys]))
    own = [*keys, "account", "node"]
    changes = held.select(*own, *[o for o in order if o not in own], "start", "k", "h", "k_all", "h_all", F.explode(F.filter("counts", lambda c: c["now"] != c["was"])).alias("c"))
    levels = changes.select("*", F.col("c.y").alias("y"), F.greatest("c.now", "c.was").alias("x"), (F.col("c.now") > F.col("c.was")).alias("rise"))
    level = Window.partitionBy(*keys, "y", "x").orderBy(*order)
    close = F.lit(period_end).cast("timestamp_ntz")
    next_ = lambda c, last: F.coalesce(F.lead(c).over(level), last)
    paired = levels.select(*own, "y", "x", "rise", F.col("start").alias("onset"), next_("start", close).alias("end"), (next_("k", F.col("k_all")) - F.col("k")).alias("tickets"), (next_("h", F.col("h_all")) - F.col("h")).alias("hours"))
    whole = counted.groupBy(*own).agg(F.min("start").alias("onset"), close.alias("end"), F.sum("tickets").alias("tickets"), F.sum("hours").alias("hours"))
    every = whole.withColumn("y", F.explode(F.array(*[F.lit(y) for y in ys]))).withColumn("x", F.lit(0).cast("long"))
    return paired.where("rise").drop("rise").unionByName(every.select(*own, "y", "x", "onset", "end", "tickets", "hours"))


def island_scores(islands: DataFrame, counted: DataFrame, tickets: DataFrame, scope: str = "device") -> DataFrame:
    """(y, x, faults, accuracy, coverage, ntr) of the faults of every setting. With scope 'node' (or 'all') faults that
    overlap within it are one, and true if any member has a ticket."""
    if scope == "device":
        faults = islands.select("y", "x", "tickets")
    else:
        place = F.col("node") if scope == "node" else F.lit(0)
        along = Window.partitionBy("y", "x", "place").orderBy("onset", "end", "account")
        reach = F.max("end").over(along.rowsBetween(Window.unboundedPreceding, -1))
        fresh = islands.withColumn("place", place).withColumn("fresh", (reach.isNull() | (F.col("onset") >= reach)).cast("int"))
        numbered = fresh.withColumn("event", F.sum("fresh").over(along.rowsBetween(Window.unboundedPreceding, 0)))
        faults = numbered.groupBy("y", "x", "place", "event").agg(F.sum("tickets").alias("tickets"))
    found = faults.groupBy("y", "x").agg(F.count(F.lit(1)).alias("faults"), F.sum((F.col("tickets") > 0).cast("int")).alias("true_faults"))
    time = islands.groupBy("y", "x").agg(F.sum("tickets").alias("detected"), F.sum("hours").alias("fault_hours"))
    whole = counted.agg(F.struct(F.sum("tickets").alias("k"), F.sum("hours").alias("h")).alias("all")).scalar()
    asked = tickets.agg(F.count(F.lit(1)).alias("n")).scalar()
    rated = found.join(time, ["y", "x"]).withColumn("all", whole).withColumn("asked", asked)
    rate = F.try_divide(ratio(F.col("detected"), F.col("fault_hours")), ratio(F.col("all.k"), F.col("all.h")))
    return rated.select("y", "x", "faults", ratio(F.col("true_faults"), F.col("faults")).alias("accuracy"), ratio(F.col("detected"), F.col("asked")).alias("coverage"), rate.alias("ntr"))


def _slim(verdicts: DataFrame, tickets: DataFrame, keys, order) -> DataFrame:
    columns = [*dict.fromkeys([*keys, "account", "node", *order, "start", "tickets", "hours", "abnormal"])]
    return staged(count_tickets(verdicts, tickets).select(*columns), "counted")


def ticket_sweep(verdicts: DataFrame, tickets: DataFrame, ys: Sequence[int], period_end: str, keys=("device",), order=("ts", "rec_id"), scope: str = "device") -> DataFrame:
    """(y, x, faults, accuracy, coverage, ntr) of all x in 0..y and all ys. verdicts has start, hours and abnormal."""
    counted = _slim(verdicts, tickets, keys, order)
    return island_scores(fault_islands(counted, ys, period_end, keys, order), counted, tickets, scope)


def compare_windows(verdicts: DataFrame, tickets: DataFrame, ys: Sequence[int], reference: int, period_end: str, floor: float = 0.15, keys=("device",), order=("ts", "rec_id"), scope: str = "device") -> DataFrame:
    """Each window size with its tuned x, against the reference size with its own: (y, x, floor_met, accuracy, coverage, ntr,
    detected, shared, overlap, both_hours, any_hours, jaccard).

    overlap is the share of the tickets found with y that the reference finds too; jaccard compares the faulty time.
    """
    counted = _slim(verdicts, tickets, keys, order)
    islands = staged(fault_islands(counted, ys, period_end, keys, order), "islands")
    chosen = staged(tune_window(island_scores(islands, counted, tickets, scope).where("x > 0"), floor), "chosen")
    picked = islands.join(F.broadcast(chosen.select("y", "x")), ["y", "x"])
    base = picked.where(F.col("y") == reference)
    met = tickets_in_faults(picked.withColumn("fault_no", F.lit(0)), tickets, ("y",)).select("y", "ticket_id").distinct()
    known = met.where(F.col("y") == reference).select("ticket_id", F.lit(1).alias("known"))
    shared = met.join(known, "ticket_id", "left").groupBy("y").agg(F.count(F.lit(1)).alias("detected"), F.count("known").alias("shared"))
    again = base.drop("y").withColumn("y", F.explode(F.array(*[F.lit(y) for y in ys])))
    time = fault_time_jaccard(picked, again, ("y",))
    return chosen.drop("faults").join(shared, "y", "left").join(time, "y", "left").withColumn("overlap", ratio(F.col("shared"), F.col("detected")))


def tune_window(sweep: DataFrame, floor: float = 0.15) -> DataFrame:
    """The chosen x of each y: (y, x, accuracy, coverage, ntr, floor_met). Settings above the coverage floor come
    first, then the product of rate and accuracy; if none reaches the floor the best row says so."""
    score = F.col("ntr") * F.col("accuracy")
    met = F.col("coverage") >= F.lit(floor)
    order = Window.partitionBy("y").orderBy(F.desc("floor_met"), F.desc_nulls_last("score"), F.desc("x"))
    return sweep.withColumn("floor_met", met).withColumn("score", score).withColumn("place", F.row_number().over(order)).where("place = 1").drop("place", "score")


def fault_time_jaccard(a: DataFrame, b: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """(by, both_hours, any_hours, jaccard) of the faulty time of two detections, by a sweep over interval edges."""
    edges = None
    for df, da, db in ((a, 1, 0), (b, 0, 1)):
        for t, sign in (("onset", 1), ("end", -1)):
            part = df.select(*by, "device", F.col(t).alias("t"), F.lit(da * sign).alias("da"), F.lit(db * sign).alias("db"))
            edges = part if edges is None else edges.unionByName(part)
    at = edges.groupBy(*by, "device", "t").agg(F.sum("da").alias("da"), F.sum("db").alias("db"))
    along = Window.partitionBy(*by, "device").orderBy("t")
    upto = along.rowsBetween(Window.unboundedPreceding, 0)
    swept = at.select(*by, "device", F.sum("da").over(upto).alias("na"), F.sum("db").over(upto).alias("nb"), hours_between(F.col("t"), F.lead("t").over(along)).alias("hours"))
    both = F.coalesce(F.sum(F.when((F.col("na") > 0) & (F.col("nb") > 0), F.col("hours"))), F.lit(0.0))
    some = F.coalesce(F.sum(F.when((F.col("na") > 0) | (F.col("nb") > 0), F.col("hours"))), F.lit(0.0))
    return swept.groupBy(*by).agg(both.alias("both_hours"), some.alias("any_hours")).withColumn("jaccard", ratio(F.col("both_hours"), F.col("any_hours")))


def ticket_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """(detected, shared, overlap): share of the tickets detected by a that b detects too; both have ticket_id."""
    one, two = a.select("ticket_id").distinct(), b.select("ticket_id").distinct()
    return one.agg(F.count(F.lit(1)).alias("detected")).withColumn("shared", one.intersect(two).agg(F.count(F.lit(1)).alias("shared")).scalar()).withColumn("overlap", ratio(F.col("shared"), F.col("detected")))


def cluster_agreement(labels: DataFrame, a: str, b: str) -> DataFrame:
    """(items, ri, ari) of two labellings, from the contingency table; never from pairs of items."""
    pairs = lambda c: F.col(c) * (F.col(c) - 1) / 2
    cells = labels.groupBy(a, b).agg(F.count(F.lit(1)).alias("n"))
    both = cells.agg(F.sum(pairs("n")).alias("p_ab"), F.sum("n").alias("items"))
    one = cells.groupBy(a).agg(F.sum("n").alias("n")).agg(F.sum(pairs("n")).alias("p_a"))
    two = cells.groupBy(b).agg(F.sum("n").alias("n")).agg(F.sum(pairs("n")).alias("p_b"))
    total = F.col("items") * (F.col("items") - 1) / 2
    expected = F.try_divide(F.col("p_a") * F.col("p_b"), total)
    ari = F.try_divide(F.col("p_ab") - expected, (F.col("p_a") + F.col("p_b")) / 2 - expected)
    ri = F.try_divide(total + 2 * F.col("p_ab") - F.col("p_a") - F.col("p_b"), total)
    return both.withColumn("p_a", one.scalar()).withColumn("p_b", two.scalar()).select("items", ri.alias("ri"), ari.alias("ari"))


# Distributions over detected tickets and faults


def detected_tickets(faults: DataFrame, tickets: DataFrame) -> DataFrame:
    """tickets inside a fault, each once, with the earliest onset of the faults that hold it."""
    met = tickets_in_faults(faults, tickets).groupBy("ticket_id").agg(F.min("onset").alias("onset"))
    return tickets.join(met, "ticket_id")


def ticket_type_counts(detected: DataFrame, by: Sequence[str] = ("action", "description")) -> DataFrame:
    return detected.groupBy(*by).agg(F.count(F.lit(1)).alias("n"))


def _summary(df: DataFrame, value: str) -> DataFrame:
    return df.agg(F.count(value).alias("n"), F.avg(value).alias("mean"), F.percentile(value, F.lit(0.5)).alias("median"), F.min(value).alias("least"), F.max(value).alias("most"))


def life_time_stats(detected: DataFrame) -> DataFrame:
    """(open, n, mean, median, least, most) of hours from creation to closing; open tickets counted apart."""
    timed = detected.withColumn("life", hours_between("created", "closed"))
    return _summary(timed, "life").withColumn("open", timed.agg(F.count(F.when(F.col("closed").isNull(), 1)).alias("open")).scalar())


def report_wait_stats(detected: DataFrame) -> DataFrame:
    """The same of hours from fault onset to the ticket."""
    return _summary(detected.withColumn("wait", hours_between("onset", "created")), "wait")


def cumulative_shares(df: DataFrame, value: str, points: Sequence[float]) -> DataFrame:
    """(at, share): how much of the values lies at or below each point; one scan."""
    marks = F.array(*[F.lit(float(p)) for p in points])
    rows = df.where(F.col(value).isNotNull()).select(F.col(value).alias("v"), F.explode(marks).alias("at"))
    return rows.groupBy("at").agg(F.avg((F.col("v") <= F.col("at")).cast("double")).alias("share"))


def fault_length_density(faults: DataFrame, width_hours: float = 24.0) -> DataFrame:
    """(bin, lo, n, density) of fault lengths in equal bins; the density integrates to 1."""
    placed = faults.groupBy(F.floor(F.col("hours") / F.lit(width_hours)).alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    total = placed.agg(F.sum("n").alias("total")).scalar()
    return placed.select("bin", (F.col("bin") * F.lit(width_hours)).alias("lo"), "n", (F.col("n") / total / F.lit(width_hours)).alias("density"))


def typed_rate_lift(counted: DataFrame) -> DataFrame:
    """Per fault type, the rate of its own kind of ticket over that kind's overall rate.

    counted has fault_type, hours, k_maintenance and k_service per record.
    """
    rates = [counted.agg(ratio(F.sum(k), F.sum("hours")).alias("rate")).scalar() for k in ("k_maintenance", "k_service")]
    by = counted.where("fault_type is not null").groupBy("fault_type").agg(F.sum("hours").alias("hours"), F.sum("k_maintenance").alias("km"), F.sum("k_service").alias("ks"))
    lift = F.when(F.col("fault_type") == "maintenance", F.try_divide(ratio(F.col("km"), F.col("hours")), rates[0])).otherwise(F.try_divide(ratio(F.col("ks"), F.col("hours")), rates[1]))
    return by.select("fault_type", "hours", "km", "ks", lift.alias("lift"))
