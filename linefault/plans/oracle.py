"""The same queries in SQL, written as plain definitions: a scan per cut, a frame per feature, a loop per pair."""

from __future__ import annotations

from ..operators.thresholds import direction_of
from ..sources.adapters import METRICS

HOURS = "date_diff('microsecond', {a}, {b}) / 3600000000.0::DOUBLE"
END = "TIMESTAMP '2024-01-31'"

BASE = """
base AS (
  SELECT e.event_id, e.ts, e.user_id AS account, c.c_nationkey::INT AS node, e.event_type, e.value,
         CAST(json_extract_string(e.props, '$.k') AS INT) AS k,
         date_diff('microsecond', TIMESTAMP '2024-01-01', e.ts) / 86400000000.0::DOUBLE AS day
  FROM events e JOIN customer c ON e.user_id = c.c_custkey),
truth AS (
  SELECT *, node % 5 = 0 AND ((day >= 3 + node % 11 AND day < 6 + node % 11) OR (day >= 19 + node % 8 AND day < 22 + node % 8)) AS maint,
         account % 4 = 1 AND node % 5 <> 0 AND ((day >= 2 + (7 * account) % 13 AND day < 5 + (7 * account) % 13)
           OR (day >= 19 + (5 * account) % 7 AND day < 22 + (5 * account) % 7)) AS serv
  FROM base),
tel AS (
  SELECT event_id AS rec_id, ts, account AS device, account, node, day,
         36 - value / 25 - CASE WHEN maint THEN 9 WHEN serv THEN 7 ELSE 0 END AS snr,
         45 + k / 50 + CASE WHEN maint THEN 6 WHEN serv THEN 5 ELSE 0 END AS tx,
         -5 + (k - 50) / 25 AS rx, 10 * value AS unerrored, k::DOUBLE AS corrected, (k % 7)::DOUBLE AS uncorrectable,
         (k % 5)::DOUBLE AS t3, (k % 3)::DOUBLE AS t4, 18 + k / 10 AS tap, maint, serv
  FROM truth WHERE event_type <> 'error'),
tkt AS (
  SELECT *, CASE WHEN is_network THEN 'Dispatch' WHEN k < 45 THEN 'Education' ELSE 'Cancelled' END AS action,
         CASE WHEN NOT is_network THEN 'Billing' WHEN k % 3 = 0 THEN 'Data Down' WHEN k % 3 = 1 THEN 'Noisy Line' ELSE 'Slow Speed' END AS description
  FROM (SELECT event_id AS ticket_id, account, node, k, ts AS created, day, CASE WHEN k % 20 <> 0 THEN ts + to_microseconds(round(value * 3600000000)::BIGINT) END AS closed,
               maint OR serv OR k >= 85 AS is_network, maint AS is_maintenance, CASE WHEN maint THEN 1000 * node::BIGINT + floor(day)::BIGINT END AS primary_id
        FROM truth WHERE event_type = 'error'))"""

HELD = f"""
ivl AS (
  SELECT *, ts AS start, coalesce(lead(ts) OVER w, {END}) AS "end" FROM tel WINDOW w AS (PARTITION BY device ORDER BY ts, rec_id)),
held AS (SELECT *, {HOURS.format(a='start', b='"end"')} AS hours FROM ivl)"""
IVL = f"{BASE},{HELD}"

PLACED = f"""{HELD},
net AS (SELECT * FROM tkt WHERE is_network),
placed AS (
  SELECT t.ticket_id, (SELECT arg_max(h.rec_id, (h.ts, h.rec_id)) FROM held h WHERE h.account = t.account AND h.ts <= t.created) AS rec_id
  FROM net t),
counted AS (
  SELECT h.*, coalesce(p.n, 0) AS tickets FROM held h LEFT JOIN (SELECT rec_id, count(*) AS n FROM placed GROUP BY rec_id) p USING (rec_id))"""
COUNTED = f"{BASE},{PLACED}"


def frame(agg: str, win: int) -> str:
    """A full window of `win` records, else null."""
    over = f"OVER (PARTITION BY device ORDER BY ts, rec_id ROWS BETWEEN {win - 1} PRECEDING AND CURRENT ROW)"
    return f"CASE WHEN count(*) {over} = {win} THEN {agg} {over} END"


def weighted(metric: str, win: int, total: float) -> str:
    terms = " + ".join(f"{win - i} * lag({metric}, {i}) OVER (PARTITION BY device ORDER BY ts, rec_id)" for i in range(win))
    return f"({terms}) / nullif({total}, 0)"


def series(value: str) -> str:
    return f"WITH {BASE} SELECT rec_id, round({value}, 6) AS value FROM tel"


def cut_scan(metric: str, direction: str, steps: int) -> str:
    side = f"{metric} < cut" if direction == "below" else f"{metric} >= cut"
    cut = "cut, NULL::DOUBLE" if direction == "below" else "NULL::DOUBLE, cut"
    return f"""WITH {COUNTED},
span AS (SELECT min({metric}) AS lo, max({metric}) AS hi FROM counted),
cuts AS (SELECT lo + j * (hi - lo) / {steps} - (hi - lo) * 1e-9 AS cut FROM span, range(1, {steps}) r(j)),
sums AS (
  SELECT cut, sum(tickets) FILTER (WHERE {side}) AS ka, sum(hours) FILTER (WHERE {side}) AS ha,
         sum(tickets) FILTER (WHERE NOT ({side})) AS kn, sum(hours) FILTER (WHERE NOT ({side})) AS hn FROM cuts, counted GROUP BY cut),
rated AS (SELECT {cut.split(', ')[0]} AS low, {cut.split(', ')[1]} AS high, *, (ka / nullif(ha, 0)) / nullif(kn / nullif(hn, 0), 0) AS trr FROM sums)
SELECT round(low, 6) AS low, round(high, 6) AS high, ka::BIGINT AS k_abn, round(ha, 4) AS h_abn, kn::BIGINT AS k_norm, round(hn, 4) AS h_norm, round(trr, 6) AS trr
FROM rated WHERE trr IS NOT NULL AND ka >= 20 ORDER BY round(rated.trr, 9) DESC, ka DESC, round(ha, 6), rated.low, rated.high LIMIT 1"""


def band_scan(metric: str, steps: int) -> str:
    side = f"coalesce({metric} < lo_cut OR {metric} >= hi_cut, {metric} < lo_cut, {metric} >= hi_cut, false)"
    return f"""WITH {COUNTED},
span AS (SELECT min({metric}) AS lo, max({metric}) AS hi FROM counted),
cuts AS (SELECT j, CASE WHEN j NOT IN (0, {steps}) THEN lo + j * (hi - lo) / {steps} - (hi - lo) * 1e-9 END AS cut FROM span, range(0, {steps} + 1) r(j)),
pairs AS (SELECT a.cut AS lo_cut, b.cut AS hi_cut FROM cuts a JOIN cuts b ON a.j < b.j),
sums AS (
  SELECT lo_cut, hi_cut, sum(tickets) FILTER (WHERE {side}) AS ka, sum(hours) FILTER (WHERE {side}) AS ha,
         sum(tickets) FILTER (WHERE NOT {side}) AS kn, sum(hours) FILTER (WHERE NOT {side}) AS hn FROM pairs, counted GROUP BY lo_cut, hi_cut),
rated AS (SELECT *, (ka / nullif(ha, 0)) / nullif(kn / nullif(hn, 0), 0) AS trr FROM sums)
SELECT round(lo_cut, 6) AS low, round(hi_cut, 6) AS high, ka::BIGINT AS k_abn, round(ha, 4) AS h_abn, kn::BIGINT AS k_norm, round(hn, 4) AS h_norm, round(trr, 6) AS trr
FROM rated WHERE trr IS NOT NULL AND ka >= 20 ORDER BY round(rated.trr, 9) DESC, ka DESC, round(ha, 6), lo_cut NULLS FIRST, hi_cut NULLS FIRST LIMIT 1"""


EWMA = f"""WITH RECURSIVE {BASE},
numbered AS (SELECT rec_id, device, snr, row_number() OVER (PARTITION BY device ORDER BY ts, rec_id) AS i FROM tel),
rolled AS (
  SELECT rec_id, device, i, snr AS e3, snr AS e7 FROM numbered WHERE i = 1
  UNION ALL
  SELECT n.rec_id, n.device, n.i, 0.3::DOUBLE * n.snr + 0.7::DOUBLE * r.e3, 0.7::DOUBLE * n.snr + 0.3::DOUBLE * r.e7 FROM rolled r JOIN numbered n ON n.device = r.device AND n.i = r.i + 1)
SELECT rec_id, round(e3, 6) AS ewma_3, round(e7, 6) AS ewma_7 FROM rolled"""

SUPPLY = """
sup AS (
  SELECT l_suppkey AS device, l_shipdate AS ts, l_orderkey, l_linenumber, l_partkey, l_extendedprice, l_quantity, l_discount, l_tax
  FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE l_returnflag <> 'R')"""


def supply_grid(metrics: tuple, wins: tuple) -> str:
    parts = []
    for m in metrics:
        for w in wins:
            over = f"OVER (PARTITION BY device ORDER BY ts, l_orderkey, l_linenumber, l_partkey, l_extendedprice ROWS BETWEEN {w - 1} PRECEDING AND CURRENT ROW)"
            for name, agg in (("avg", "avg"), ("var", "var_pop")):
                parts.append(f"SELECT '{m}-{name}-{w}' AS feature, count(v) AS n, round(avg(v), 4) AS mean FROM (SELECT CASE WHEN count(*) {over} = {w} THEN {agg}({m}) {over} END AS v FROM sup)")
    return f"WITH {SUPPLY} " + " UNION ALL ".join(parts)


# The whole method: every feature of every record, every cut of every feature, the choice, and the verdicts


def wide(metrics: tuple, days: range, tenths: range, per_day: int) -> str:
    """CTEs up to `long` (rec_id, feature, value): frames for the windowed models, a recursion for the exponential ones."""
    row = "PARTITION BY device ORDER BY ts, rec_id"
    cols, names = [], []
    for m in metrics:
        for d in days:
            w = d * per_day
            mean = f"CASE WHEN count({m}) OVER w{w} = {w} THEN avg({m}) OVER w{w} END"
            walk = " + ".join(f"{w - i} * lag({m}, {i}) OVER ({row})" for i in range(w))
            wma = f"({walk}) / {w * (w + 1) / 2}"
            cols += [f'{mean} AS "{m}-avg-{d}"', f'{wma} AS "{m}-wma-{d}"', f'{m} - {wma} AS "{m}-wma-diff-{d}"', f'CASE WHEN count({m}) OVER w{w} = {w} THEN var_pop({m}) OVER w{w} END AS "{m}-var-{d}"']
            names += [f"{m}-{x}-{d}" for x in ("avg", "wma", "wma-diff", "var")]
    frames = ", ".join(f"w{d * per_day} AS ({row} ROWS BETWEEN {d * per_day - 1} PRECEDING AND CURRENT ROW)" for d in days)
    smooth = [(m, t) for m in metrics for t in tenths]
    first = ", ".join(f'{m} AS "{m}-ewma-{t}"' for m, t in smooth)
    step = ", ".join(f'{t / 10}::DOUBLE * n.{m} + {(10 - t) / 10}::DOUBLE * r."{m}-ewma-{t}"' for m, t in smooth)
    return f"""framed AS MATERIALIZED (SELECT rec_id, {", ".join(cols)} FROM tel WINDOW {frames}),
numbered AS MATERIALIZED (SELECT *, row_number() OVER ({row}) AS i FROM tel),
rolled AS (
  SELECT rec_id, device, i, {first} FROM numbered WHERE i = 1
  UNION ALL SELECT n.rec_id, n.device, n.i, {step} FROM rolled r JOIN numbered n ON n.device = r.device AND n.i = r.i + 1),
long AS MATERIALIZED (
  SELECT rec_id, feature, value FROM framed UNPIVOT (value FOR feature IN ({", ".join(f'"{n}"' for n in names)}))
  UNION ALL SELECT rec_id, feature, value FROM (SELECT * EXCLUDE (device, i) FROM rolled) UNPIVOT (value FOR feature IN ({", ".join(f'"{m}-ewma-{t}"' for m, t in smooth)})))"""


def scored(metrics: tuple, days: range, tenths: range, side, end: str, until: float, guards: tuple, steps: int = 100, band_steps: int = 40) -> str:
    """CTEs after `long` up to `best`: for each feature the best cut over the records before day `until`. What lies below a
    cut comes from running sums over the sorted values."""
    grid = [(m, x, p) for m in metrics for x in ("avg", "wma", "ewma", "wma-diff", "var") for p in (tenths if x == "ewma" else days)]
    listed = ", ".join(f"('{m}-{x}-{p}', '{m}', '{x}', {p}, '{side(f'{m}-{x}-{p}')}')" for m, x, p in grid)
    least, low_share, high_share = guards
    return f"""kind(feature, metric, model, param, side) AS (VALUES {listed}),
early AS (SELECT *, ts AS start, coalesce(lead(ts) OVER (PARTITION BY device ORDER BY ts, rec_id), {end}) AS "end" FROM tel WHERE day < {until}),
early_tickets AS (
  SELECT (SELECT arg_max(h.rec_id, (h.ts, h.rec_id)) FROM early h WHERE h.account = t.account AND h.ts <= t.created) AS rec_id FROM tkt t WHERE t.is_network AND t.day < {until}),
weighed AS MATERIALIZED (
  SELECT e.rec_id, {HOURS.format(a='start', b='"end"')} AS hours, coalesce(p.n, 0) AS tickets
  FROM early e LEFT JOIN (SELECT rec_id, count(*) AS n FROM early_tickets GROUP BY rec_id) p USING (rec_id)),
valued AS MATERIALIZED (SELECT feature, value, sum(tickets) AS k, sum(hours) AS h FROM long JOIN weighed USING (rec_id) GROUP BY feature, value),
running AS MATERIALIZED (SELECT feature, value, sum(k) OVER (PARTITION BY feature ORDER BY value) AS k, sum(h) OVER (PARTITION BY feature ORDER BY value) AS h FROM valued),
span AS (SELECT feature, min(value) AS lo, max(value) AS hi, sum(k) AS k_all, sum(h) AS h_all FROM valued GROUP BY feature HAVING min(value) < max(value)),
cuts AS (
  SELECT feature, side, j, CASE WHEN side = 'band' THEN {band_steps} ELSE {steps} END AS n, lo + j * (hi - lo) / CASE WHEN side = 'band' THEN {band_steps} ELSE {steps} END - (hi - lo) * 1e-9 AS cut, k_all, h_all
  FROM span JOIN kind USING (feature), range(0, {steps} + 1) r(j) WHERE j <= CASE WHEN side = 'band' THEN {band_steps} ELSE {steps} END),
under AS MATERIALIZED (
  SELECT c.feature, c.side, c.j, c.n, c.cut, c.k_all, c.h_all, CASE WHEN c.j = c.n THEN c.k_all WHEN c.j = 0 THEN 0 ELSE coalesce(r.k, 0) END AS k, CASE WHEN c.j = c.n THEN c.h_all WHEN c.j = 0 THEN 0 ELSE coalesce(r.h, 0) END AS h
  FROM cuts c ASOF LEFT JOIN running r ON c.feature = r.feature AND c.cut > r.value),
tried AS (
  SELECT feature, 'below' AS direction, cut AS low, NULL::DOUBLE AS high, k AS k_abn, h AS h_abn, k_all - k AS k_norm, h_all - h AS h_norm FROM under WHERE side IN ('below', 'auto')
  UNION ALL SELECT feature, 'above', NULL, cut, k_all - k, h_all - h, k, h FROM under WHERE side IN ('above', 'auto')
  UNION ALL SELECT a.feature, 'band', CASE WHEN a.j > 0 THEN a.cut END, CASE WHEN b.j < b.n THEN b.cut END, a.k_all - b.k + a.k, a.h_all - (b.h - a.h), b.k - a.k, b.h - a.h
    FROM under a JOIN under b ON a.feature = b.feature AND a.j < b.j WHERE a.side = 'band'),
rated AS (SELECT *, (k_abn / nullif(h_abn, 0)) / nullif(k_norm / nullif(h_norm, 0), 0) AS trr FROM tried),
best AS MATERIALIZED (
  SELECT rated.*, metric, model, param FROM rated JOIN kind USING (feature)
  WHERE trr IS NOT NULL AND k_abn >= {least} AND h_abn BETWEEN {low_share} * (h_abn + h_norm) AND {high_share} * (h_abn + h_norm)
  QUALIFY row_number() OVER (PARTITION BY feature ORDER BY round(trr, 9) DESC, k_abn DESC, round(h_abn, 6), direction, low NULLS FIRST, high NULLS FIRST) = 1),
represented AS (SELECT * FROM best QUALIFY row_number() OVER (PARTITION BY metric, model ORDER BY round(trr, 9) DESC, feature) = 1),
top_models AS (SELECT * FROM represented QUALIFY row_number() OVER (PARTITION BY metric ORDER BY round(trr, 9) DESC, feature) <= 2)"""


def verdicts(n: int) -> str:
    """CTEs after `scored`: the chosen features, what fires in each record, and the abnormal records."""
    return f"""chosen AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY round(trr, 9) DESC, feature) AS place FROM top_models ORDER BY round(trr, 9) DESC, feature LIMIT {n}),
firing AS MATERIALIZED (SELECT rec_id, feature, place FROM long JOIN chosen USING (feature) WHERE value < low OR value >= high),
abn AS MATERIALIZED (SELECT DISTINCT rec_id FROM firing)"""


SCORE_ROWS = "feature, metric, model, param::INT AS param, direction, round(low, 6) AS low, round(high, 6) AS high, k_abn::BIGINT AS k_abn, round(h_abn, 4) AS h_abn, k_norm::BIGINT AS k_norm, round(h_norm, 4) AS h_norm, round(trr, 6) AS trr"

TRAIN_END, TRAIN_DAYS, GUARDS, KEPT = "TIMESTAMP '2024-01-20'", 19, (20, 0.005, 0.25), 5
SEARCHED = f"{BASE}, {wide(METRICS, range(1, 8), range(1, 10), 2)}, {scored(METRICS, range(1, 8), range(1, 10), direction_of, TRAIN_END, TRAIN_DAYS, GUARDS)}"
DETECTED = f"{SEARCHED}, {verdicts(KEPT)}"
#: Telemetry, tickets, the fitted detector and its verdicts: what the queries after detection start from.
CHAIN = f"WITH RECURSIVE {DETECTED},{PLACED}"
XY = (2, 4)
RULE = "rec_id IN (SELECT rec_id FROM abn)"


def marks(x: int, y: int, rule: str = RULE) -> str:
    return f"""
marks AS MATERIALIZED (
  SELECT *, hits >= {x} AS marked FROM (
    SELECT *, {rule} AS abnormal,
           sum(CASE WHEN {rule} THEN 1 ELSE 0 END) OVER (PARTITION BY device ORDER BY ts, rec_id ROWS BETWEEN {y - 1} PRECEDING AND CURRENT ROW)::BIGINT AS hits,
           first_value(start) OVER (PARTITION BY device ORDER BY ts, rec_id ROWS BETWEEN {y - 1} PRECEDING AND CURRENT ROW) AS oldest FROM counted))"""


def faults(x: int, y: int, onset: str = "min(start)") -> str:
    return f"""{marks(x, y)},
runs AS (
  SELECT *, row_number() OVER (PARTITION BY device ORDER BY ts, rec_id) - row_number() OVER (PARTITION BY device, marked ORDER BY ts, rec_id) AS island,
         lead(start) OVER (PARTITION BY device ORDER BY ts, rec_id) AS next_start FROM marks),
grouped AS (
  SELECT device, any_value(account) AS account, any_value(node) AS node, {onset} AS onset, max(coalesce(next_start, {END})) AS fend,
         count(*) AS points, max(hits) AS peak, bool_or(next_start IS NULL) AS "open" FROM runs WHERE marked GROUP BY device, island),
flt AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY device ORDER BY onset, fend) AS fault_no, {HOURS.format(a='onset', b='fend')} AS hours FROM grouped),
met AS MATERIALIZED (SELECT t.*, f.device, f.fault_no, f.onset, f.fend FROM net t JOIN flt f ON f.account = t.account AND t.created >= f.onset AND t.created < f.fend)"""


MARKS = f"{CHAIN},{marks(*XY)}"
FAULTS = f"{CHAIN},{faults(*XY)}"

SCORES = """SELECT (SELECT count(*) FROM flt) AS faults, (SELECT count(*) FROM (SELECT DISTINCT device, fault_no FROM met)) AS true_faults,
  round((SELECT count(*) FROM (SELECT DISTINCT device, fault_no FROM met)) / (SELECT count(*) FROM flt), 6) AS accuracy,
  (SELECT count(DISTINCT ticket_id) FROM met) AS detected, (SELECT count(*) FROM net) AS tickets,
  round((SELECT count(DISTINCT ticket_id) FROM met) / (SELECT count(*) FROM net), 6) AS coverage,
  round(((SELECT count(DISTINCT ticket_id) FROM met) / (SELECT sum(hours) FROM flt)) / ((SELECT count(rec_id) FROM placed) / (SELECT sum(hours) FROM held)), 6) AS ntr"""

MERGED = """,
merged AS (
  SELECT node, sum(fresh) OVER (PARTITION BY node ORDER BY onset, fend, device, fault_no) AS event_no, onset, fend, account FROM (
    SELECT *, CASE WHEN max(fend) OVER (PARTITION BY node ORDER BY onset, fend, device, fault_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) > onset THEN 0 ELSE 1 END AS fresh FROM flt)),
event AS (SELECT node, event_no, min(onset) AS onset, max(fend) AS fend, count(*) AS faults FROM merged GROUP BY node, event_no)"""

# Window settings


def islands(ys, rule: str = RULE, end: str = END, order: str = "ts, rec_id") -> str:
    """CTE isl: the faults of every y and every x in 0..y, from each record's own membership in each level."""
    return f"""
flagged AS MATERIALIZED (
  SELECT device, account, node, start, tickets, hours, row_number() OVER w AS i, lead(start) OVER w AS next_start, sum(({rule})::INT) OVER (PARTITION BY device ORDER BY {order} ROWS UNBOUNDED PRECEDING) AS c
  FROM counted WINDOW w AS (PARTITION BY device ORDER BY {order})),
levels AS (SELECT a.*, y, a.c - coalesce(b.c, 0) AS hits FROM flagged a CROSS JOIN (SELECT unnest({list(ys)}) AS y) LEFT JOIN flagged b ON b.device = a.device AND b.i = a.i - y),
inside AS (SELECT *, unnest(range(0, hits::BIGINT + 1)) AS x FROM levels),
numbered_levels AS (SELECT *, i - row_number() OVER (PARTITION BY device, y, x ORDER BY i) AS island FROM inside),
isl AS MATERIALIZED (
  SELECT device, any_value(account) AS account, any_value(node) AS node, y, x, min(start) AS onset, max(coalesce(next_start, {end})) AS fend, sum(tickets) AS tickets, sum(hours) AS hours
  FROM numbered_levels GROUP BY device, y, x, island),
swept AS MATERIALIZED (
  SELECT y, x, count(*) AS faults, avg((tickets > 0)::INT) AS accuracy, sum(tickets) / (SELECT count(*) FROM net) AS coverage,
         (sum(tickets) / sum(hours)) / ((SELECT sum(tickets) FROM counted) / (SELECT sum(hours) FROM counted)) AS ntr FROM isl GROUP BY y, x)"""


NODE_SWEEP = """,
begun AS (SELECT *, CASE WHEN max(fend) OVER (PARTITION BY y, x, node ORDER BY onset, fend, account ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) > onset THEN 0 ELSE 1 END AS fresh FROM isl),
eventful AS (SELECT *, sum(fresh) OVER (PARTITION BY y, x, node ORDER BY onset, fend, account ROWS UNBOUNDED PRECEDING) AS event FROM begun),
by_node AS (SELECT y, x, count(*) AS faults, avg(hit::INT) AS accuracy FROM (SELECT y, x, node, event, sum(tickets) > 0 AS hit FROM eventful GROUP BY ALL) GROUP BY y, x)"""

SWEEP_ROWS = "y::INT AS y, x::BIGINT AS x, faults, round(accuracy, 6) AS accuracy, round(coverage, 6) AS coverage, round(ntr, 6) AS ntr"
TUNED = ",\ntuned AS MATERIALIZED (SELECT *, coverage >= 0.15 AS floor_met FROM swept WHERE x > 0 QUALIFY row_number() OVER (PARTITION BY y ORDER BY coverage >= 0.15 DESC, round(ntr * accuracy, 9) DESC NULLS LAST, x DESC) = 1)"


def against(reference: int) -> str:
    """CTEs after TUNED: ticket overlap and faulty time of every y against the reference, piece by piece of time."""
    return f""",
picked AS MATERIALIZED (SELECT isl.* FROM isl JOIN tuned USING (y, x)),
found AS (SELECT DISTINCT y, ticket_id FROM net t JOIN picked p ON p.account = t.account AND t.created >= p.onset AND t.created < p.fend),
overlapping AS (SELECT y, count(*) AS detected, count(*) FILTER (WHERE ticket_id IN (SELECT ticket_id FROM found WHERE y = {reference})) AS shared FROM found GROUP BY y),
edge AS (
  SELECT y, device, onset AS t FROM picked UNION SELECT y, device, fend FROM picked
  UNION SELECT t.y, device, onset FROM picked p, tuned t WHERE p.y = {reference} UNION SELECT t.y, device, fend FROM picked p, tuned t WHERE p.y = {reference}),
piece AS (SELECT y, device, t, lead(t) OVER (PARTITION BY y, device ORDER BY t) AS u FROM edge),
tested AS (
  SELECT y, {HOURS.format(a='t', b='u')} AS hours, EXISTS (SELECT 1 FROM picked f WHERE f.y = p.y AND f.device = p.device AND f.onset <= t AND f.fend > t) AS a,
         EXISTS (SELECT 1 FROM picked f WHERE f.y = {reference} AND f.device = p.device AND f.onset <= t AND f.fend > t) AS b FROM piece p WHERE u IS NOT NULL),
timed AS (SELECT y, coalesce(sum(hours) FILTER (WHERE a AND b), 0) AS both_hours, coalesce(sum(hours) FILTER (WHERE a OR b), 0) AS any_hours FROM tested GROUP BY y)"""


# Several verdicts side by side


def by_group(flags: str, x: int = XY[0], y: int = XY[1], where: str = "true") -> str:
    """CTEs g_flt and g_met: faults and tickets in them for each group g of the flags (g, rec_id, abnormal)."""
    return f"""
flags AS MATERIALIZED ({flags}),
g_marks AS (
  SELECT *, lead(start) OVER (PARTITION BY g, device ORDER BY ts, rec_id) AS next_start FROM (
    SELECT f.g, c.*, sum(f.abnormal::INT) OVER (PARTITION BY g, device ORDER BY ts, rec_id ROWS BETWEEN {y - 1} PRECEDING AND CURRENT ROW) >= {x} AS marked
    FROM flags f JOIN counted c USING (rec_id) WHERE {where})),
g_runs AS (SELECT *, row_number() OVER (PARTITION BY g, device ORDER BY ts, rec_id) - row_number() OVER (PARTITION BY g, device, marked ORDER BY ts, rec_id) AS island FROM g_marks),
g_flt AS MATERIALIZED (
  SELECT *, {HOURS.format(a='onset', b='fend')} AS hours FROM (
    SELECT g, device, any_value(account) AS account, island, min(start) AS onset, max(coalesce(next_start, {END})) AS fend FROM g_runs WHERE marked GROUP BY g, device, island)),
g_met AS MATERIALIZED (SELECT f.g, t.*, f.device, f.island, f.onset, f.fend FROM net t JOIN g_flt f ON f.account = t.account AND t.created >= f.onset AND t.created < f.fend WHERE {where}),
g_time AS (SELECT sum(hours) AS h, (SELECT count(*) FROM net t JOIN (SELECT account, min(start) AS begun FROM counted WHERE {where} GROUP BY account) b USING (account) WHERE {where} AND t.created >= b.begun) AS k FROM counted WHERE {where}),
g_scores AS (
  SELECT g, (SELECT count(*) FROM g_flt f WHERE f.g = e.g) AS faults, (SELECT count(*) FROM (SELECT DISTINCT device, island FROM g_met m WHERE m.g = e.g)) / (SELECT count(*) FROM g_flt f WHERE f.g = e.g) AS accuracy,
         (SELECT count(DISTINCT ticket_id) FROM g_met m WHERE m.g = e.g) / (SELECT count(*) FROM net WHERE {where}) AS coverage,
         ((SELECT count(DISTINCT ticket_id) FROM g_met m WHERE m.g = e.g) / (SELECT sum(hours) FROM g_flt f WHERE f.g = e.g)) / (SELECT k / h FROM g_time) AS ntr
  FROM (SELECT DISTINCT g FROM flags) e),
g_det AS (SELECT m.g, t.*, m.onset AS m_onset FROM net t JOIN (SELECT g, ticket_id, min(onset) AS onset FROM g_met GROUP BY g, ticket_id) m USING (ticket_id))"""


# Clusters


def linkage(fold: str, floor: float) -> str:
    """CTEs after items (g, item) and sims (g, a, b, sim): `grown`, every state of merging the two most similar clusters of each
    group by the fold of all their members' similarities, with the similarity of the last merge."""
    return f"""
grown AS (
  SELECT g, item, item AS cluster, 0 AS step, 9.0::DOUBLE AS s FROM items
  UNION ALL
  (WITH pairs AS (
     SELECT x.g, least(x.cluster, y.cluster) AS keep, greatest(x.cluster, y.cluster) AS gone, {fold}(p.sim) AS s
     FROM sims p JOIN grown x ON x.g = p.g AND x.item = p.a JOIN grown y ON y.g = p.g AND y.item = p.b WHERE x.cluster <> y.cluster GROUP BY 1, 2, 3),
   next_merge AS (SELECT * FROM pairs WHERE s >= {floor} QUALIFY row_number() OVER (PARTITION BY g ORDER BY s DESC, keep, gone) = 1)
   SELECT r.g, r.item, CASE WHEN r.cluster = n.gone THEN n.keep ELSE r.cluster END, r.step + 1, n.s FROM grown r JOIN next_merge n ON n.g = r.g))"""


def cut(cuts) -> str:
    """CTE labelled (g, item, cut, cluster, size) at each cut."""
    return f"""
labelled AS MATERIALIZED (
  SELECT *, count(*) OVER (PARTITION BY g, cut, cluster) AS size FROM (
    SELECT g, item, cut, arg_max(cluster, step) AS cluster FROM grown, (SELECT unnest({[float(c) for c in cuts]}::DOUBLE[]) AS cut) WHERE s >= cut GROUP BY g, item, cut))"""


def density(cuts, least: int = 4) -> str:
    """CTE labelled for density clusters: cores by their neighbours, their components, and the first component next to a border."""
    return f"""
cut_list AS (SELECT unnest({[float(c) for c in cuts]}::DOUBLE[]) AS cut),
near AS MATERIALIZED (SELECT cut, g, a, b FROM (SELECT g, a, b, sim FROM sims UNION ALL SELECT g, b, a, sim FROM sims), cut_list WHERE sim >= cut),
core AS MATERIALIZED (SELECT cut, g, item FROM (SELECT c.cut, i.g, i.item, 1 + (SELECT count(*) FROM near n WHERE n.cut = c.cut AND n.g = i.g AND n.a = i.item) AS k FROM items i, cut_list c) WHERE k >= {least}),
joined AS MATERIALIZED (SELECT n.cut, n.g, n.a, n.b FROM near n JOIN core x ON x.cut = n.cut AND x.g = n.g AND x.item = n.a JOIN core y ON y.cut = n.cut AND y.g = n.g AND y.item = n.b),
reached AS (SELECT cut, g, item AS a, item AS b FROM core UNION SELECT r.cut, r.g, r.a, j.b FROM reached r JOIN joined j ON j.cut = r.cut AND j.g = r.g AND j.a = r.b),
root AS MATERIALIZED (SELECT cut, g, a AS item, min(b) AS label FROM reached GROUP BY ALL),
labelled AS MATERIALIZED (
  SELECT *, count(*) OVER (PARTITION BY g, cut, cluster) AS size FROM (
    SELECT i.g, i.item, c.cut, coalesce(r.label, (SELECT min(o.label) FROM near n JOIN root o ON o.cut = n.cut AND o.g = n.g AND o.item = n.b WHERE n.cut = c.cut AND n.g = i.g AND n.a = i.item), i.item) AS cluster
    FROM items i CROSS JOIN cut_list c LEFT JOIN root r ON r.cut = c.cut AND r.g = i.g AND r.item = i.item))"""


PERIOD, LOOK_BACK, EVERY = 72, 168, 12
SLOT = "floor(date_diff('microsecond', TIMESTAMP '2024-01-01', {}) / (72 * 3600000000.0::DOUBLE))::INT"


def period_vectors(metrics) -> str:
    """CTEs after marks: anomalous (device, node, slot) and vec (metric, node, slot, device, v)."""
    held = ", ".join(f"(SELECT arg_max({m}, (ts, rec_id)) FROM tel t WHERE t.device = p.device AND t.ts <= p.moment) AS {m}" for m in metrics)
    back = ", ".join(f"coalesce({m}, first_value({m} IGNORE NULLS) OVER (PARTITION BY device ORDER BY moment ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), 0) AS {m}" for m in metrics)
    parts = " UNION ALL ".join(
        f"""SELECT '{m}' AS metric, a.node, a.slot, a.device, list(p.{m} ORDER BY p.moment) AS v FROM anomalous a JOIN filled p ON p.device = a.device
    AND p.moment >= TIMESTAMP '2024-01-01' + to_hours(a.slot * {PERIOD} + {PERIOD - LOOK_BACK}) AND p.moment < TIMESTAMP '2024-01-01' + to_hours(a.slot * {PERIOD} + {PERIOD}) GROUP BY ALL"""
        for m in metrics
    )
    return f"""
anomalous AS MATERIALIZED (SELECT DISTINCT device, node, {SLOT.format('ts')} AS slot FROM marks WHERE marked),
points AS (SELECT device, g.moment FROM (SELECT DISTINCT device FROM anomalous), generate_series(TIMESTAMP '2024-01-01', TIMESTAMP '2024-01-30 12:00:00', INTERVAL {EVERY} HOURS) g(moment)),
filled AS MATERIALIZED (SELECT device, moment, {back} FROM (SELECT *, {held} FROM points p)),
vec AS MATERIALIZED ({parts}),
centred AS MATERIALIZED (SELECT metric || ':' || node || ':' || slot AS g, metric, node, slot, device, [x - list_avg(v) for x in v] AS v FROM vec),
items AS MATERIALIZED (SELECT g, device AS item FROM centred),
sims AS MATERIALIZED (
  SELECT p.g, p.metric, p.node, p.slot, p.device AS a, q.device AS b,
         CASE WHEN list_dot_product(p.v, p.v) > 1e-24 AND list_dot_product(q.v, q.v) > 1e-24 THEN list_dot_product(p.v, q.v) / (sqrt(list_dot_product(p.v, p.v)) * sqrt(list_dot_product(q.v, q.v))) ELSE 0 END AS sim
  FROM centred p JOIN centred q ON p.g = q.g AND p.device < q.device)"""


def period_types(metrics, cuts) -> str:
    """CTEs after marks up to typed (metric, node, slot, device, cut, cluster, size, fault_type) by average linkage."""
    return f"""{period_vectors(metrics)},{linkage('avg', min(cuts))},{cut(cuts)},
typed AS MATERIALIZED (
  SELECT c.metric, c.node, c.slot, c.device, l.cut, l.cluster, l.size, CASE WHEN l.size >= 2 THEN 'maintenance' ELSE 'service' END AS fault_type
  FROM labelled l JOIN centred c ON c.g = l.g AND c.device = l.item)"""


TYPED_TIME = f""",
back AS (SELECT m.*, coalesce(lag(ts) OVER (PARTITION BY device ORDER BY ts, rec_id), ts) AS since FROM marks m),
shared_tickets AS (
  SELECT t.ticket_id, (SELECT arg_min(b.rec_id, (b.ts, b.rec_id)) FROM back b WHERE b.account = t.account AND b.ts >= t.created) AS rec_id FROM tkt t WHERE t.is_maintenance),
impaired AS MATERIALIZED (
  SELECT b.device, {SLOT.format('b.ts')} AS slot, {HOURS.format(a='since', b='ts')} AS hours, (SELECT count(*) FROM shared_tickets s WHERE s.rec_id = b.rec_id) AS tickets FROM back b WHERE marked),
rated_types AS MATERIALIZED (
  SELECT metric, cut, coalesce(sum(tickets) FILTER (WHERE fault_type = 'maintenance'), 0) AS k_mm, coalesce(sum(hours) FILTER (WHERE fault_type = 'maintenance'), 0) AS h_m,
         coalesce(sum(tickets) FILTER (WHERE fault_type = 'service'), 0) AS k_ms, coalesce(sum(hours) FILTER (WHERE fault_type = 'service'), 0) AS h_s
  FROM typed JOIN impaired USING (device, slot) GROUP BY metric, cut)"""

FITTED_TYPES = """,
chosen_cut AS MATERIALIZED (
  SELECT metric, coalesce((SELECT cut FROM rated_types r WHERE r.metric = m.metric AND k_mm >= 5 AND k_ms > 0 AND h_m > 0 AND h_s > 0 ORDER BY round((k_mm / h_m) / (k_ms / h_s), 9) DESC, cut DESC LIMIT 1), 0.95) AS cut
  FROM (VALUES ('snr'), ('tx')) m(metric)),
fitted_types AS MATERIALIZED (
  SELECT device, slot, CASE WHEN bool_or(fault_type = 'maintenance') THEN 'maintenance' ELSE 'service' END AS fault_type FROM typed JOIN chosen_cut USING (metric, cut) GROUP BY device, slot)"""

SUPPLY_CLOSE = "TIMESTAMP '2001-12-31'"
SUPPLY_KEY = "ts, l_orderkey, l_linenumber, l_partkey, l_extendedprice"
#: The long series as records with their tickets, by the day.
LONG = f"""sup AS (SELECT l_suppkey AS device, l_suppkey AS account, s_nationkey::INT AS node, l_shipdate AS ts, l_orderkey, l_linenumber, l_partkey, l_extendedprice, l_quantity FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE l_returnflag <> 'R'),
dated AS (SELECT *, ts AS start, coalesce(lead(ts) OVER w, TIMESTAMP '2001-12-31') AS "end", coalesce(lead(ts) OVER w, TIMESTAMP '9999-01-01') AS following FROM sup WINDOW w AS (PARTITION BY device ORDER BY {SUPPLY_KEY})),
net AS (SELECT l_suppkey AS account, l_shipdate AS created FROM lineitem WHERE l_returnflag = 'R'),
counted AS MATERIALIZED (
  SELECT h.*, {HOURS.format(a='start', b='"end"')} AS hours, (SELECT count(*) FROM net t WHERE t.account = h.account AND t.created >= h.start AND t.created < h.following) AS tickets FROM dated h)"""
