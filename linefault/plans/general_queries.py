"""Traces, roll-ups and the general operators around the methods."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import columns as C
from ..sources import adapters as A
from ..sources.readers import read_table
from . import oracle as O
from .base import counted, flt, tel
from .book import query, rounded

@query("q_traces", f"""WITH {O.BASE}, k AS (SELECT *, CASE WHEN maint THEN 'shared' WHEN serv THEN 'distinct' ELSE 'normal' END AS kind FROM tel)
SELECT node, floor(day)::BIGINT AS day, round(avg(tx) FILTER (WHERE kind = 'normal'), 4) AS normal, round(avg(tx) FILTER (WHERE kind = 'shared'), 4) AS shared, round(avg(tx) FILTER (WHERE kind = 'distinct'), 4) AS "distinct" FROM k GROUP BY ALL""")
def q_traces(s, d):
    """Daily mean transmit power of the devices of each node: the planted shared, distinct and normal patterns side by side."""
    rows = tel(s, d).withColumn("kind", F.when(F.col("maint"), "shared").when(F.col("serv"), "distinct").otherwise("normal"))
    return rows.groupBy("node", F.floor("day").alias("day")).pivot("kind", ["normal", "shared", "distinct"]).agg(F.round(F.avg("tx"), 4))


@query("g_rollup", f"WITH {O.COUNTED} SELECT n_regionkey::INT AS region, c.node, sum(tickets)::BIGINT AS tickets, round(sum(hours), 4) AS hours FROM counted c JOIN nation ON n_nationkey = c.node GROUP BY ROLLUP (n_regionkey, c.node)")
def g_rollup(s, d):
    """Rates by market and node: where faults lie, as far as the tables know."""
    places = read_table(s, d, "nation").select(F.col("n_nationkey").cast("int").alias("node"), F.col("n_regionkey").cast("int").alias("region"))
    return counted(s, d).join(places, "node").rollup("region", "node").agg(F.sum("tickets").alias("tickets"), F.round(F.sum("hours"), 4).alias("hours"))


@query("g_pivot", f"WITH {O.BASE} SELECT node, count(*) FILTER (WHERE action = 'Dispatch') AS Dispatch, count(*) FILTER (WHERE action = 'Education') AS Education, count(*) FILTER (WHERE action = 'Cancelled') AS Cancelled FROM tkt GROUP BY node")
def g_pivot(s, d):
    return A.tickets(s, d).groupBy("node").pivot("action", ["Dispatch", "Education", "Cancelled"]).agg(F.count(F.lit(1))).na.fill(0)


@query("g_silent", f"WITH {O.BASE} SELECT DISTINCT device FROM tel WHERE maint AND account NOT IN (SELECT account FROM tkt WHERE is_maintenance)")
def g_silent(s, d):
    """Devices in a planted outage whose customers never say so."""
    told = A.tickets(s, d).where("is_maintenance").select(F.col("account").alias("device"))
    return tel(s, d).where("maint").select("device").distinct().join(told, "device", "left_anti")


@query("g_worst", f"WITH {O.BASE} SELECT node, rec_id, round(snr, 6) AS snr FROM tel QUALIFY row_number() OVER (PARTITION BY node ORDER BY snr, rec_id) <= 3")
def g_worst(s, d):
    place = F.row_number().over(Window.partitionBy("node").orderBy("snr", "rec_id"))
    return tel(s, d).withColumn("p", place).where("p <= 3").select("node", "rec_id", *rounded("snr"))


@query("g_sessions", f"""WITH {O.BASE}, g AS (SELECT *, CASE WHEN ts > lag(ts) OVER (PARTITION BY device ORDER BY ts) + INTERVAL 24 HOURS OR lag(ts) OVER (PARTITION BY device ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS fresh FROM tel WHERE snr < 29),
i AS (SELECT *, sum(fresh) OVER (PARTITION BY device ORDER BY ts) AS no FROM g) SELECT device, min(ts) AS onset, count(*) AS points FROM i GROUP BY device, no""")
def g_sessions(s, d):
    sessions = tel(s, d).where("snr < 29").groupBy("device", F.session_window("ts", "24 hours 1 microsecond"))
    return sessions.agg(F.min("ts").alias("onset"), F.count(F.lit(1)).alias("points")).select("device", "onset", "points")


@query("g_tumbling", f"WITH {O.BASE} SELECT node, date_trunc('day', ts) AS start, count(*) AS records, sum((snr < 29)::INT)::BIGINT AS abnormal_records FROM tel GROUP BY ALL")
def g_tumbling(s, d):
    days = tel(s, d).groupBy("node", F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("records"), F.sum((F.col("snr") < 29).cast("int")).alias("abnormal_records"))
    return days.select("node", F.col("window.start").cast("timestamp_ntz").alias("start"), "records", "abnormal_records")


@query("g_ranks", f"WITH {O.BASE}, m AS (SELECT node, round(avg(snr), 6) AS snr FROM tel GROUP BY node) SELECT node, snr, rank() OVER (ORDER BY snr)::INT AS place, ntile(4) OVER (ORDER BY snr, node)::INT AS quarter, round(percent_rank() OVER (ORDER BY snr), 6) AS share FROM m")
def g_ranks(s, d):
    """Ranks over the nodes: one row each, so that a window without partition is small."""
    means = tel(s, d).groupBy("node").agg(F.round(F.avg("snr"), 6).alias("snr"))
    along = Window.orderBy("snr")
    return means.select("node", "snr", F.rank().over(along).alias("place"), F.ntile(4).over(Window.orderBy("snr", "node")).alias("quarter"), F.round(F.percent_rank().over(along), 6).alias("share"))


@query("g_atypical_hours", f"WITH {O.BASE} SELECT extract('hour' FROM created)::INT AS hour, extract('isodow' FROM created)::INT % 7 + 1 AS weekday, count(*) AS n FROM tkt GROUP BY ALL")
def g_atypical_hours(s, d):
    return A.tickets(s, d).groupBy(F.hour("created").alias("hour"), F.dayofweek("created").alias("weekday")).agg(F.count(F.lit(1)).alias("n"))


@query("g_severity", f"{O.FAULTS} SELECT device, onset, round(peak * ln(1 + hours), 6) AS severity FROM flt QUALIFY row_number() OVER (ORDER BY round(peak * ln(1 + hours), 9) DESC, device, onset) <= 20")
def g_severity(s, d):
    """Extension: the twenty faults to look at first, by their peak count and length."""
    exact = F.round(F.col("peak") * F.log1p("hours"), 9)
    ranked = flt(s, d).select("device", "onset", exact.alias("severity")).orderBy(F.desc("severity"), "device", "onset").limit(20)
    return ranked.select("device", "onset", *rounded("severity"))


@query("g_reports_within", "SELECT o_orderpriority AS severity, o_orderstatus AS status, count(*) AS n, round(avg(l_quantity), 6) AS mean_hours FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' GROUP BY ALL")
def g_reports_within(s, d):
    hours = C.hours_between("created", "closed")
    return A.supply_tickets(s, d).groupBy("severity", "status").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(hours), 6).alias("mean_hours"))


@query("g_reporters", f"WITH {O.BASE} SELECT account FROM tkt WHERE is_maintenance INTERSECT SELECT account FROM tkt WHERE is_network AND NOT is_maintenance")
def g_reporters(s, d):
    """Set operators: accounts that report both kinds of trouble."""
    rows = A.tickets(s, d).where("is_network")
    return rows.where("is_maintenance").select("account").intersect(rows.where("not is_maintenance").select("account"))


@query("g_only_service", f"WITH {O.BASE} SELECT account FROM tkt WHERE is_network AND NOT is_maintenance EXCEPT SELECT account FROM tkt WHERE is_maintenance")
def g_only_service(s, d):
    rows = A.tickets(s, d).where("is_network")
    return rows.where("not is_maintenance").select("account").exceptAll(rows.where("is_maintenance").select("account")).distinct().join(rows.where("is_maintenance").select("account"), "account", "left_anti")


@query("g_cube", f"WITH {O.BASE} SELECT action, is_maintenance, count(*) AS n FROM tkt GROUP BY CUBE (action, is_maintenance)")
def g_cube(s, d):
    return A.tickets(s, d).cube("action", "is_maintenance").agg(F.count(F.lit(1)).alias("n"))


@query("g_unpivot", f"WITH {O.BASE} SELECT metric, count(*) AS n, round(avg(value), 4) AS mean FROM (SELECT snr, tx, rx, tap FROM tel) UNPIVOT (value FOR metric IN (snr, tx, rx, tap)) GROUP BY metric")
def g_unpivot(s, d):
    long = tel(s, d).select("snr", "tx", "rx", "tap").unpivot([], ["snr", "tx", "rx", "tap"], "metric", "value")
    return long.groupBy("metric").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 4).alias("mean"))
