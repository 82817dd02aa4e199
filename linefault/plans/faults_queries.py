"""From verdicts to faults, and the measures of faults. Everything starts from the fitted detector."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import hours_between
from ..operators import baselines as B
from ..operators import faults as FL
from ..operators import measures as M
from ..operators import selection as S
from ..sources import adapters as A
from ..sources.readers import read_table
from . import oracle as O
from .base import END, SPLIT, START, TRAIN_DAYS, X, Y, flt, held, marks, model, net, tel, train_scores, typer, types, verdicts
from .book import query, rounded
from .detector import choose_feature_count

# Verdicts


def fixed_rules(s, d, rule: str, k: int = 1) -> DataFrame:
    tests = [("snr", F.col("snr") < 29), ("tx", F.col("tx") >= 50), ("rx", F.col("rx") < -6)]
    return S.combine(tel(s, d), tests, rule, k).select("rec_id", "abnormal", F.array_join("fired", ",").alias("fired"))


def fixed_sql(test: str) -> str:
    n = "((snr < 29)::INT + (tx >= 50)::INT + (rx < -6)::INT)"
    return f"WITH {O.BASE} SELECT rec_id, {n} {test} AS abnormal, concat_ws(',', CASE WHEN snr < 29 THEN 'snr' END, CASE WHEN tx >= 50 THEN 'tx' END, CASE WHEN rx < -6 THEN 'rx' END) AS fired FROM tel"


@query("c_or", fixed_sql(">= 1"))
def c_or(s, d):
    return fixed_rules(s, d, "or")


@query("c_and", fixed_sql("= 3"))
def c_and(s, d):
    return fixed_rules(s, d, "and")


@query("c_two", fixed_sql(">= 2"))
def c_two(s, d):
    return fixed_rules(s, d, "k", 2)


@query("c_raw", f"WITH {O.BASE} SELECT rec_id, snr < 28 OR snr > 36.5 AS abnormal FROM tel")
def c_raw(s, d):
    return B.raw_limit(tel(s, d), "snr", 28.0, 36.5).select("rec_id", "abnormal")


def fired_sql(test: str) -> str:
    return f"{O.CHAIN}, f AS (SELECT rec_id, count(*) AS n, string_agg(feature, ',' ORDER BY place) AS fired FROM firing GROUP BY rec_id) SELECT rec_id, coalesce(n, 0) {test} AS abnormal, coalesce(fired, '') AS fired FROM tel LEFT JOIN f USING (rec_id)"


def fitted(s, d, rule: str, k: int = 1) -> DataFrame:
    return model(s, d).transform(tel(s, d), rule, k).select("rec_id", "abnormal", F.array_join("fired", ",").alias("fired"))


@query("c_detector", fired_sql(">= 1"))
def c_detector(s, d):
    """The detector's verdict: any of its features suffices."""
    return fitted(s, d, "or")


@query("c_detector_and", fired_sql(">= (SELECT greatest(count(*), 1) FROM chosen)"))
def c_detector_and(s, d):
    return fitted(s, d, "and")


@query("c_detector_two", fired_sql(">= 2"))
def c_detector_two(s, d):
    return fitted(s, d, "k", 2)


def count_flags(n: int) -> str:
    return f"SELECT n AS g, rec_id, EXISTS (SELECT 1 FROM firing f WHERE f.rec_id = c.rec_id AND f.place <= n) AS abnormal FROM counted c, (SELECT unnest(range(1, {n} + 1)) AS n) WHERE n <= (SELECT count(*) FROM chosen)"


@query("s_feature_count", f"""{O.CHAIN},{O.by_group(count_flags(O.KEPT))},
sides AS (SELECT g, sum(tickets) FILTER (WHERE abnormal) AS ka, sum(hours) FILTER (WHERE abnormal) AS ha, sum(tickets) FILTER (WHERE NOT abnormal) AS kn, sum(hours) FILTER (WHERE NOT abnormal) AS hn FROM flags JOIN counted USING (rec_id) GROUP BY g)
SELECT g::INT AS n, round((ka / ha) / (kn / hn), 6) AS trr, faults, round(accuracy, 6) AS accuracy, round(coverage, 6) AS coverage, round(ntr, 6) AS ntr FROM g_scores JOIN sides USING (g)""")
def s_feature_count(s, d):
    """Accuracy, coverage and rate as more features are kept."""
    out = choose_feature_count(train_scores(s, d), tel(s, d), net(s, d), A.POINTS_PER_DAY, O.KEPT, X, Y, END)
    return out.select("n", *rounded("trr"), "faults", *rounded("accuracy", "coverage", "ntr"))


@query("w_split", f"WITH {O.BASE} SELECT CASE WHEN ts < TIMESTAMP '2024-01-19' THEN 'train' ELSE 'test' END AS part, count(*) AS n FROM tel WHERE ts < TIMESTAMP '2024-01-19' OR ts >= TIMESTAMP '2024-01-20' GROUP BY 1")
def w_split(s, d):
    """A split with a day that belongs to neither part."""
    train, test = S.time_split(tel(s, d), START, "2024-01-19", END, SPLIT)
    n = F.count(F.lit(1)).alias("n")
    return train.groupBy(F.lit("train").alias("part")).agg(n).unionByName(test.groupBy(F.lit("test").alias("part")).agg(n))


# Windows and faults


@query("w_marks", f"{O.MARKS} SELECT rec_id, hits, marked FROM marks")
def w_marks(s, d):
    return marks(s, d).select("rec_id", "hits", "marked")


@query("w_marks_strict", f"{O.CHAIN},{O.marks(X + 1, Y)} SELECT rec_id, hits, marked FROM marks")
def w_marks_strict(s, d):
    return marks(s, d, strict=True).select("rec_id", "hits", "marked")


def fault_rows(f: DataFrame) -> DataFrame:
    return f.select("device", "onset", F.col("end").alias("fault_end"), *rounded("hours"), "points", "peak", "open")


FAULT_SQL = 'SELECT device, onset, fend AS fault_end, round(hours, 6) AS hours, points, peak, "open" FROM flt'


@query("w_faults", f"{O.FAULTS} {FAULT_SQL}")
def w_faults(s, d):
    return fault_rows(flt(s, d))


@query("w_faults_span", f"{O.CHAIN},{O.faults(X, Y, 'arg_min(oldest, (ts, rec_id))')} {FAULT_SQL}")
def w_faults_span(s, d):
    return fault_rows(flt(s, d, extent="span"))


@query("w_merge", f"{O.FAULTS}{O.MERGED} SELECT node::VARCHAR AS scope, onset, fend AS fault_end, faults::BIGINT AS faults FROM event")
def w_merge(s, d):
    return FL.merge_simultaneous(flt(s, d)).select("scope", "onset", F.col("end").alias("fault_end"), "faults")


MERGED_ALL = O.MERGED.replace("PARTITION BY node ORDER", "ORDER").replace("node, sum(fresh)", "0 AS node, sum(fresh)")


@query("w_merge_all", f"{O.FAULTS}{MERGED_ALL} SELECT onset, fend AS fault_end, faults::BIGINT AS faults FROM event")
def w_merge_all(s, d):
    return FL.merge_simultaneous(flt(s, d), "all").select("onset", F.col("end").alias("fault_end"), "faults")


@query("w_tickets", f"{O.FAULTS} SELECT ticket_id, device, onset FROM met")
def w_tickets(s, d):
    return FL.tickets_in_faults(flt(s, d), net(s, d)).select("ticket_id", "device", "onset")


TYPES_SQL = f"{O.period_types(('snr', 'tx'), [round(0.05 * i, 2) for i in range(20)])}{O.TYPED_TIME}{O.FITTED_TYPES}"


@query("w_dispatch", f"""{O.FAULTS},{TYPES_SQL} SELECT f.device, f.node, f.onset AS "at", coalesce(t.fault_type, 'any') AS technician
FROM flt f LEFT JOIN fitted_types t ON t.device = f.device AND t.slot = {O.SLOT.format('f.onset')}""")
def w_dispatch(s, d):
    """Whom to send at each onset: the type is that of the device in the period of the onset."""
    return FL.dispatch_decisions(flt(s, d), types(s, d), START, typer().period_hours).select("device", "node", "at", "technician")


@query("d_call", f"""{O.MARKS},{TYPES_SQL},
p AS (SELECT t.ticket_id, (SELECT arg_max([m.hits, m.device, {O.SLOT.format('m.ts')}], (m.ts, m.rec_id)) FROM marks m WHERE m.account = t.account AND m.ts <= t.created) AS m FROM tkt t)
SELECT ticket_id, m[1]::BIGINT AS hits, coalesce(m[1] >= {X}, false) AS network_cause, CASE WHEN m[1] >= {X} THEN t.fault_type END AS fault_type FROM p LEFT JOIN fitted_types t ON t.device = m[2] AND t.slot = m[3]""")
def d_call(s, d):
    """Every ticket read as a call: is the network the cause, and of which kind is the fault."""
    out = FL.diagnose_calls(A.tickets(s, d), marks(s, d), X, types=types(s, d), start=START, period_hours=typer().period_hours)
    return out.select("ticket_id", "hits", "network_cause", "fault_type")


@query("q_monitor", f"{O.MARKS} SELECT rec_id, abnormal, hits, marked, marked AND NOT coalesce(lag(marked) OVER (PARTITION BY device ORDER BY ts, rec_id), false) AS dispatch FROM marks")
def q_monitor(s, d):
    """Continuous monitoring: the telemetry replayed as a stream through the fitted detector, against the batch result."""
    from .experiments import replayed

    return replayed(s, tel(s, d), model(s, d), X, Y, A.POINTS_PER_DAY).select("rec_id", "abnormal", "hits", "marked", "dispatch")


# Measures


@query("m_scores", f"{O.FAULTS} {O.SCORES}")
def m_scores(s, d):
    return M.fault_scores(flt(s, d), net(s, d), held(s, d)).select("faults", "true_faults", *rounded("accuracy"), "detected", "tickets", *rounded("coverage", "ntr"))


@query("m_scores_node", f"""{O.FAULTS}{O.MERGED}, hit AS (SELECT DISTINCT e.node, e.event_no FROM event e JOIN merged m USING (node, event_no) JOIN net t ON t.account = m.account AND t.created >= e.onset AND t.created < e.fend)
SELECT (SELECT count(*) FROM event) AS faults, (SELECT count(*) FROM hit) AS true_faults, round((SELECT count(*) FROM hit) / (SELECT count(*) FROM event), 6) AS accuracy""")
def m_scores_node(s, d):
    return M.fault_scores(flt(s, d), net(s, d), held(s, d), "node").select("faults", "true_faults", *rounded("accuracy"))


def two_settings(y1: int, y2: int) -> str:
    """Tuned x of two window sizes, as in the window study."""
    return f"{O.CHAIN},{O.islands((y1, y2))}{O.TUNED}{O.against(y2)}"


@query("m_jaccard", f"{two_settings(6, 12)} SELECT round(coalesce(both_hours, 0), 4) AS both_hours, round(coalesce(any_hours, 0), 4) AS any_hours, round(both_hours / any_hours, 6) AS jaccard FROM (SELECT 6 AS y) LEFT JOIN timed USING (y)")
def m_jaccard(s, d):
    """Faulty time of a window of 6 against one of 12, each with its tuned x."""
    a, b = tuned_pair(s, d, 6, 12)
    return M.fault_time_jaccard(a, b).select(F.round("both_hours", 4).alias("both_hours"), F.round("any_hours", 4).alias("any_hours"), *rounded("jaccard"))


@query("m_overlap", f"{two_settings(6, 12)} SELECT coalesce(detected, 0) AS detected, coalesce(shared, 0) AS shared, round(shared / detected, 6) AS overlap FROM (SELECT 6 AS y) LEFT JOIN overlapping USING (y)")
def m_overlap(s, d):
    """Tickets that a window of 6 finds, and those of them that one of 12 finds."""
    a, b = tuned_pair(s, d, 6, 12)
    met = lambda f: FL.tickets_in_faults(f, net(s, d))
    return M.ticket_overlap(met(a), met(b)).select("detected", "shared", *rounded("overlap"))


def tuned_pair(s, d, *ys: int) -> list[DataFrame]:
    chosen = {r["y"]: int(r["x"]) for r in M.tune_window(M.ticket_sweep(verdicts(s, d), net(s, d), ys, END).where("x > 0")).collect()}
    return [flt(s, d, chosen.get(y, y), y) for y in ys]


YS = (1, 4, 6)


@query("m_sweep", f"{O.CHAIN},{O.islands(YS)} SELECT {O.SWEEP_ROWS} FROM swept")
def m_sweep(s, d):
    return M.ticket_sweep(verdicts(s, d), net(s, d), YS, END).select("y", "x", "faults", *rounded("accuracy", "coverage", "ntr"))


@query("w_tune", f"{O.CHAIN},{O.islands(YS)}{O.TUNED} SELECT y::INT AS y, x::BIGINT AS x, floor_met, round(accuracy, 6) AS accuracy FROM tuned")
def w_tune(s, d):
    return M.tune_window(M.ticket_sweep(verdicts(s, d), net(s, d), YS, END).where("x > 0")).select("y", "x", "floor_met", *rounded("accuracy"))


@query("q_xy", f"{O.CHAIN},{O.islands((12,))} SELECT {O.SWEEP_ROWS} FROM swept")
def q_xy(s, d):
    """x = 0...12 at y = 12. With x = 0 all time is faulty and the rate is 1."""
    return M.ticket_sweep(verdicts(s, d), net(s, d), (12,), END).select("y", "x", "faults", *rounded("accuracy", "coverage", "ntr"))


@query("q_xy_node", f"{O.CHAIN},{O.islands((12,))}{O.NODE_SWEEP} SELECT y::INT AS y, x::BIGINT AS x, n.faults, round(n.accuracy, 6) AS accuracy, round(coverage, 6) AS coverage, round(ntr, 6) AS ntr FROM by_node n JOIN swept s USING (y, x)")
def q_xy_node(s, d):
    """The same with faults of several devices of a node at one time counted once."""
    return M.ticket_sweep(verdicts(s, d), net(s, d), (12,), END, scope="node").select("y", "x", "faults", *rounded("accuracy", "coverage", "ntr"))


SIZES = range(1, 61)


@query("q_windows", f"{O.CHAIN},{O.islands(SIZES)}{O.TUNED} SELECT {O.SWEEP_ROWS}, floor_met FROM tuned")
def q_windows(s, d):
    """The tuned x of every window size from 1 to 60."""
    return M.tune_window(M.ticket_sweep(verdicts(s, d), net(s, d), SIZES, END).where("x > 0")).select("y", "x", "faults", *rounded("accuracy", "coverage", "ntr"), "floor_met")


@query("q_window_overlap", f"""{O.CHAIN},{O.islands(SIZES)}{O.TUNED}{O.against(12)}
SELECT t.y::INT AS y, t.x::BIGINT AS x, detected, shared, round(shared / detected, 6) AS overlap, round(both_hours, 4) AS both_hours, round(any_hours, 4) AS any_hours, round(both_hours / any_hours, 6) AS jaccard
FROM tuned t LEFT JOIN overlapping USING (y) LEFT JOIN timed USING (y)""")
def q_window_overlap(s, d):
    """Tickets and faulty time of every tuned window size against those of 12."""
    out = M.compare_windows(verdicts(s, d), net(s, d), SIZES, 12, END)
    return out.select("y", "x", "detected", "shared", *rounded("overlap"), F.round("both_hours", 4).alias("both_hours"), F.round("any_hours", 4).alias("any_hours"), *rounded("jaccard"))


@query("q_windows_long", f"WITH {O.LONG},{O.islands(SIZES, 'l_quantity > 45', O.SUPPLY_CLOSE, O.SUPPLY_KEY)}{O.TUNED} SELECT {O.SWEEP_ROWS}, floor_met FROM tuned")
def q_windows_long(s, d):
    """Every window size on the long series, whose windows of 60 are full."""
    held_ = S.combine(_long(s, d), [("l_quantity", F.col("l_quantity") > 45)])
    swept = M.ticket_sweep(held_, A.supply_tickets(s, d), SIZES, A.SUPPLY_END, order=A.SUPPLY_ORDER)
    return M.tune_window(swept.where("x > 0")).select("y", "x", "faults", *rounded("accuracy", "coverage", "ntr"), "floor_met")


def _long(s, d) -> DataFrame:
    from ..operators.rates import held_intervals

    return held_intervals(A.supply_telemetry(s, d), A.SUPPLY_END, order=A.SUPPLY_ORDER)


@query("m_rand", """WITH l AS (SELECT label AS a, vec_id % 7 AS b FROM embeddings), c AS (SELECT a, b, count(*) AS n FROM l GROUP BY a, b),
 p AS (SELECT sum(n * (n - 1) / 2) AS ab, sum(n) AS m, (SELECT sum(t * (t - 1) / 2) FROM (SELECT sum(n) AS t FROM c GROUP BY a)) AS pa, (SELECT sum(t * (t - 1) / 2) FROM (SELECT sum(n) AS t FROM c GROUP BY b)) AS pb FROM c)
SELECT m::BIGINT AS items, round((m * (m - 1) / 2 + 2 * ab - pa - pb) / (m * (m - 1) / 2), 6) AS ri, round((ab - pa * pb / (m * (m - 1) / 2)) / ((pa + pb) / 2 - pa * pb / (m * (m - 1) / 2)), 6) AS ari FROM p""")
def m_rand(s, d):
    labels = read_table(s, d, "embeddings").select(F.col("label").alias("a"), (F.col("vec_id") % 7).alias("b"))
    return M.cluster_agreement(labels, "a", "b").select("items", *rounded("ri", "ari"))


# Tools side by side: the detector and the operator's tools, one window rule, measured on the test days

BANDED = ("snr", "tx", "rx")


def bands(s, d) -> list[B.Band]:
    return B.quantile_bands(tel(s, d).where(F.col("day") < TRAIN_DAYS), BANDED, exact=True)


BANDS_SQL = "".join(f", q_{m} AS (SELECT quantile_cont({m}, 0.01) AS a, quantile_cont({m}, 0.05) AS b, quantile_cont({m}, 0.95) AS c, quantile_cont({m}, 0.99) AS d FROM tel WHERE day < {TRAIN_DAYS})" for m in BANDED)
LEVEL = "greatest(" + ", ".join(f"CASE WHEN {m} BETWEEN q_{m}.b AND q_{m}.c THEN 0 WHEN {m} BETWEEN q_{m}.a AND q_{m}.d THEN 1 ELSE 2 END" for m in BANDED) + ")"
POINTS = " + ".join(f"({m} < q_{m}.b)::INT + ({m} > q_{m}.c)::INT" for m in BANDED)
TOOLS = ("detector", "bands", "scoreboard")
TOOL_FLAGS = f"SELECT 'detector' AS g, rec_id, {O.RULE} AS abnormal FROM counted UNION ALL SELECT 'bands', rec_id, {LEVEL} > 0 FROM counted, q_snr, q_tx, q_rx UNION ALL SELECT 'scoreboard', rec_id, {POINTS} > 1 FROM counted, q_snr, q_tx, q_rx"
TOOLS_SQL = f"{O.CHAIN}{BANDS_SQL},{O.by_group(TOOL_FLAGS, where=f'day >= {TRAIN_DAYS}')}"


def late(df: DataFrame) -> DataFrame:
    return df.where(F.col("day") >= TRAIN_DAYS)


def tool_faults(s, d) -> dict[str, DataFrame]:
    """Faults of each tool in the test days."""
    limits = bands(s, d)
    flags = {"detector": verdicts(s, d), "bands": B.colour_bands(held(s, d), limits), "scoreboard": B.scoreboard(held(s, d), B.band_rules(limits))}
    return {name: FL.fault_events(S.mark_windows(late(flags[name]), X, Y), END, Y) for name in TOOLS}


def by_tool(s, d, measure) -> DataFrame:
    """A measure of the detected tickets (or of the faults) of each tool, with its method."""
    out = None
    for name, faults in tool_faults(s, d).items():
        part = measure(faults).withColumn("method", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


def detected(s, d):
    return lambda faults: M.detected_tickets(faults, late(net(s, d)))


@query("q_tools", f"{TOOLS_SQL} SELECT g AS method, faults, round(accuracy, 6) AS accuracy, round(coverage, 6) AS coverage, round(ntr, 6) AS ntr FROM g_scores")
def q_tools(s, d):
    """Accuracy, coverage and rate of the detector and the operator's tools."""
    return by_tool(s, d, lambda f: M.fault_scores(f, late(net(s, d)), late(held(s, d)))).select("method", "faults", *rounded("accuracy", "coverage", "ntr"))


LIFE = O.HOURS.format(a="created", b="closed")


@query("st_types", f"{TOOLS_SQL} SELECT g AS method, action, description, count(*) AS n FROM g_det GROUP BY ALL")
def st_types(s, d):
    return by_tool(s, d, lambda f: M.ticket_type_counts(detected(s, d)(f)))


@query("st_life", f"{TOOLS_SQL}, l AS (SELECT g, closed, {LIFE} AS v FROM g_det) SELECT g AS method, count(*) FILTER (WHERE closed IS NULL) AS open_tickets, count(v) AS n, round(avg(v), 6) AS mean, round(median(v), 6) AS median FROM l GROUP BY g")
def st_life(s, d):
    return by_tool(s, d, lambda f: M.life_time_stats(detected(s, d)(f))).where("n > 0 or open > 0").select("method", F.col("open").alias("open_tickets"), "n", *rounded("mean", "median"))


@query("st_life_cdf", f"""{TOOLS_SQL}, l AS (SELECT g, {LIFE} AS v FROM g_det WHERE closed IS NOT NULL), p(point) AS (VALUES (12.0::DOUBLE), (24.0), (48.0), (96.0), (192.0))
SELECT g AS method, point AS "at", round(avg((v <= point)::INT), 6) AS share FROM l, p GROUP BY g, point""")
def st_life_cdf(s, d):
    life = lambda f: detected(s, d)(f).withColumn("life", hours_between("created", "closed"))
    return by_tool(s, d, lambda f: M.cumulative_shares(life(f), "life", (12, 24, 48, 96, 192))).select("method", "at", *rounded("share"))


@query("st_wait", f"{TOOLS_SQL}, w AS (SELECT g, {O.HOURS.format(a='m_onset', b='created')} AS v FROM g_det) SELECT g AS method, count(v) AS n, round(avg(v), 6) AS mean, round(median(v), 6) AS median FROM w GROUP BY g")
def st_wait(s, d):
    return by_tool(s, d, lambda f: M.report_wait_stats(detected(s, d)(f))).where("n > 0").select("method", "n", *rounded("mean", "median"))


@query("st_wait_cdf", f"""{TOOLS_SQL}, l AS (SELECT g, {O.HOURS.format(a='m_onset', b='created')} AS v FROM g_det), p(point) AS (VALUES (12.0::DOUBLE), (24.0), (48.0), (96.0), (192.0))
SELECT g AS method, point AS "at", round(avg((v <= point)::INT), 6) AS share FROM l, p GROUP BY g, point""")
def st_wait_cdf(s, d):
    wait = lambda f: detected(s, d)(f).withColumn("wait", hours_between("onset", "created"))
    return by_tool(s, d, lambda f: M.cumulative_shares(wait(f), "wait", (12, 24, 48, 96, 192))).select("method", "at", *rounded("share"))


@query("st_length", f"{TOOLS_SQL} SELECT f.g AS method, floor(hours / 24)::BIGINT AS bin, count(*) AS n, round(count(*) / any_value(t.n) / 24, 8) AS density FROM g_flt f JOIN (SELECT g, count(*) AS n FROM g_flt GROUP BY g) t USING (g) GROUP BY f.g, 2")
def st_length(s, d):
    return by_tool(s, d, M.fault_length_density).select("method", "bin", "n", F.round("density", 8).alias("density"))


@query("b_bands", f"WITH {O.BASE}{BANDS_SQL} SELECT rec_id, ['green', 'yellow', 'red'][{LEVEL} + 1] AS level, {LEVEL} > 0 AS abnormal FROM tel, q_snr, q_tx, q_rx")
def b_bands(s, d):
    return B.colour_bands(tel(s, d), bands(s, d)).select("rec_id", "level", "abnormal")


@query("b_board", f"WITH {O.BASE}{BANDS_SQL} SELECT rec_id, ({POINTS})::DOUBLE AS points, {POINTS} > 1 AS abnormal FROM tel, q_snr, q_tx, q_rx")
def b_board(s, d):
    return B.scoreboard(tel(s, d), B.band_rules(bands(s, d))).select("rec_id", "points", "abnormal")


def flagged_sql(ratio_: str, limit: float) -> str:
    return f"""{ratio_}, r AS (SELECT vec_id, day, tap_db < {limit} AS bad FROM t)
SELECT day, count(DISTINCT vec_id) AS devices, count(DISTINCT vec_id) FILTER (WHERE bad) AS flagged, round(count(DISTINCT vec_id) FILTER (WHERE bad) / count(DISTINCT vec_id), 6) AS share FROM r GROUP BY ROLLUP (day)"""


ENERGY = "WITH e AS (SELECT vec_id, (vec_id % 5)::INT AS day, [x::DOUBLE * x::DOUBLE for x in embedding] AS e FROM embeddings)"


@query("b_tap", flagged_sql(f"{ENERGY}, t AS (SELECT vec_id, day, 10 * log10((e[17] + e[18]) / (list_sum(e) - e[17] - e[18])) AS tap_db FROM e)", -12))
def b_tap(s, d):
    return B.flagged_share(B.tap_ratio_flags(A.taps(s, d), -12.0)).select("day", "devices", "flagged", *rounded("share"))


@query("b_tap_18db", flagged_sql(f"{ENERGY}, o AS (SELECT *, list_sum(e) - e[17] - e[18] AS rest FROM e), t AS (SELECT vec_id, day, 10 * log10(rest * power(10, (9.5 + vec_id % 16) / 10) / rest) AS tap_db FROM o)", 18))
def b_tap_18db(s, d):
    """The recommended limit of 18 dB, over equalisers that lie on both sides of it."""
    return B.flagged_share(B.tap_ratio_flags(A.tap_vectors(s, d), 18.0)).select("day", "devices", "flagged", *rounded("share"))

