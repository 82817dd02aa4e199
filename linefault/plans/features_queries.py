"""Features of the planted telemetry (windows of two days are four records), rates and thresholds."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import columns as C
from ..functions.naming import feature_grid
from ..operators import features as FE
from ..operators import grid as G
from ..operators import rates as R
from ..operators import selection as S
from ..operators import thresholds as T
from ..sources import adapters as A
from ..sources.readers import read_table
from . import oracle as O
from .base import END, GUARD, START, counted, held, net, tel, train_scores
from .book import query, rounded


def snr_feature(s, d, value) -> DataFrame:
    """rec_id and one feature of snr; value is made here, as columns need a session."""
    row = F.row_number().over(Window.partitionBy("device").orderBy("ts", "rec_id"))
    return tel(s, d).withColumn("snr__r", row * F.col("snr")).select("rec_id", F.round(value(), 6).alias("value"))


@query("f_avg", O.series(O.frame("avg(snr)", 4)))
def f_avg(s, d):
    return snr_feature(s, d, lambda: FE.moving_average("snr", 4))


@query("f_wma", O.series(O.weighted("snr", 4, 10)))
def f_wma(s, d):
    return snr_feature(s, d, lambda: FE.weighted_average("snr", 4))


@query("f_wma_printed", O.series(O.weighted("snr", 4, 6)))
def f_wma_printed(s, d):
    return snr_feature(s, d, lambda: FE.weighted_average("snr", 4, denominator="printed"))


@query("f_wmadiff", O.series(f"snr - {O.weighted('snr', 4, 10)}"))
def f_wmadiff(s, d):
    return snr_feature(s, d, lambda: F.col("snr") - FE.weighted_average("snr", 4))


@query("f_var", O.series(O.frame("var_pop(snr)", 4)))
def f_var(s, d):
    return snr_feature(s, d, lambda: FE.moving_variance("snr", 4))


@query("f_shrink", O.series("avg(snr) OVER (PARTITION BY device ORDER BY ts, rec_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW)"))
def f_shrink(s, d):
    return snr_feature(s, d, lambda: FE.moving_average("snr", 4, partial="shrink"))


@query("f_ewma", O.EWMA)
def f_ewma(s, d):
    built = FE.build_features(tel(s, d), feature_grid(["snr"], (), (3, 7)), A.POINTS_PER_DAY)
    return built.select("rec_id", F.round("snr_ewma_3", 6).alias("ewma_3"), F.round("snr_ewma_7", 6).alias("ewma_7"))


@query("f_ewma_fold", O.EWMA.replace("SELECT rec_id, round(e3, 6) AS ewma_3, round(e7, 6) AS ewma_7 FROM rolled", "SELECT device, round(arg_max(e3, i), 6) AS ewma_3 FROM rolled GROUP BY device"))
def f_ewma_fold(s, d):
    points = F.array_sort(F.collect_list(F.struct("ts", "rec_id", "snr")))
    packed = tel(s, d).groupBy("device").agg(points.alias("p")).select("device", F.transform("p", lambda x: x["snr"]).alias("v"))
    return packed.select("device", F.round(FE.exponential_fold("snr", 0.3, "v"), 6).alias("ewma_3"))


DELTA = "CASE WHEN corrected >= lag(corrected) OVER w THEN corrected - lag(corrected) OVER w WHEN lag(corrected) OVER w IS NOT NULL THEN corrected END"


@query("f_delta", O.series(DELTA) + " WINDOW w AS (PARTITION BY device ORDER BY ts, rec_id)")
def f_delta(s, d):
    return snr_feature(s, d, lambda: FE.counter_delta("corrected"))


@query("f_range", O.series("avg(snr) OVER (PARTITION BY device ORDER BY date_trunc('second', ts) RANGE BETWEEN INTERVAL 259199 SECONDS PRECEDING AND CURRENT ROW)"))
def f_range(s, d):
    return snr_feature(s, d, lambda: FE.range_average("snr", 3))


@query("f_tap", """WITH t AS (SELECT vec_id, [x::DOUBLE * x::DOUBLE for x in embedding] AS e FROM embeddings)
SELECT vec_id AS device, (vec_id % 5)::INT AS day, round(10 * log10((e[17] + e[18]) / nullif(list_sum(e) - e[17] - e[18], 0)), 6) AS tap_db FROM t""")
def f_tap(s, d):
    return A.taps(s, d).select("device", "day", *rounded("tap_db"))


@query("f_hold", f"""WITH {O.BASE}, slots AS (SELECT DISTINCT device, g.slot FROM tel, generate_series(TIMESTAMP '2024-01-01', TIMESTAMP '2024-01-30 12:00:00', INTERVAL 12 HOURS) g(slot))
SELECT device, slot, round((SELECT arg_max(snr, (ts, rec_id)) FROM tel t WHERE t.device = s.device AND t.ts <= s.slot), 6) AS value FROM slots s""")
def f_hold(s, d):
    return FE.resample_hold(tel(s, d), "snr", START, END, 12).select("device", "slot", *rounded("value"))


WINS = (1, 2, 4, 8, 14)


@query("f_grid", O.supply_grid(("l_quantity", "l_discount"), WINS))
def f_grid(s, d):
    """Part of the grid over long series, natively."""
    grid = [f for f in feature_grid(["l_quantity", "l_discount"], WINS, ()) if f.model in ("avg", "var")]
    built = FE.build_features(A.supply_telemetry(s, d), grid, 1, order=A.SUPPLY_ORDER)
    row = built.agg(*[F.struct(F.count(f.column).alias("n"), F.round(F.avg(f.column), 4).alias("mean")).alias(f.column) for f in grid])
    named = [F.struct(F.lit(f.name).alias("feature"), F.col(f"{f.column}.n").alias("n"), F.col(f"{f.column}.mean").alias("mean")) for f in grid]
    return row.select(F.explode(F.array(*named)).alias("x")).select("x.*")


@query("f_grid_all", f"WITH RECURSIVE {O.BASE}, {O.wide(A.METRICS, range(1, 8), range(1, 10), A.POINTS_PER_DAY)} SELECT feature, count(*) AS n, round(avg(value), 4) AS mean FROM long GROUP BY feature")
def f_grid_all(s, d):
    """The whole grid of 37 features of every metric: 333 features in one pass over packed series."""
    packed = G.pack_series(tel(s, d), A.METRICS, extra=())
    return G.grid_summary(packed, feature_grid(A.METRICS), A.POINTS_PER_DAY).select("feature", "n", F.round("mean", 4).alias("mean"))


# Rates


@query("t_intervals", f"WITH {O.IVL} SELECT rec_id, start, \"end\", round(hours, 6) AS hours FROM held")
def t_intervals(s, d):
    return held(s, d).select("rec_id", "start", "end", *rounded("hours"))


@query("t_intervals_back", f"WITH {O.BASE}, b AS (SELECT rec_id, ts, coalesce(lag(ts) OVER (PARTITION BY device ORDER BY ts, rec_id), ts) AS p FROM tel) SELECT rec_id, round({O.HOURS.format(a='p', b='ts')}, 6) AS hours FROM b")
def t_intervals_back(s, d):
    return held(s, d, "backward").select("rec_id", *rounded("hours"))


@query("t_attach", f"WITH {O.COUNTED} SELECT ticket_id, rec_id FROM placed")
def t_attach(s, d):
    return R.tickets_in_force(held(s, d), net(s, d)).select("ticket_id", "rec_id")


@query("t_rate", f"WITH {O.COUNTED} SELECT node, sum(tickets)::BIGINT AS tickets, round(sum(hours), 4) AS hours, round(sum(tickets) / sum(hours), 8) AS rate FROM counted GROUP BY node")
def t_rate(s, d):
    rate = C.ratio(F.sum("tickets"), F.sum("hours"))
    return counted(s, d).groupBy("node").agg(F.sum("tickets").alias("tickets"), F.round(F.sum("hours"), 4).alias("hours"), F.round(rate, 8).alias("rate"))


def curve_rows(curve: DataFrame) -> DataFrame:
    return curve.select("bin", *rounded("lo", "hi"), "tickets", F.round("hours", 4).alias("hours"), *rounded("rate_over_base"))


def curve_sql(counted_: str, metric: str) -> str:
    return f"""WITH {counted_}, v AS (SELECT {metric} AS lo, sum(tickets) AS k, sum(hours) AS h FROM counted GROUP BY 1), overall AS (SELECT sum(tickets) / sum(hours) AS b FROM counted)
SELECT row_number() OVER (ORDER BY lo)::INT AS bin, round(lo, 6) AS lo, round(lead(lo) OVER (ORDER BY lo), 6) AS hi, k::BIGINT AS tickets, round(h, 4) AS hours, round(k / h / b, 6) AS rate_over_base FROM v, overall"""


def binned_sql(counted_: str, metric: str, bins: int) -> str:
    return f"""WITH {counted_}, overall AS (SELECT sum(tickets) / sum(hours) AS b, quantile_cont({metric}, {[i / bins for i in range(1, bins)]}) AS edges FROM counted),
v AS (SELECT len([e for e in list_distinct(edges) if e <= {metric}])::INT + 1 AS bin, {metric} AS m, tickets, hours, b FROM counted, overall)
SELECT bin, round(min(m), 6) AS lo, round(max(m), 6) AS hi, sum(tickets)::BIGINT AS tickets, round(sum(hours), 4) AS hours, round(sum(tickets) / sum(hours) / any_value(b), 6) AS rate_over_base FROM v GROUP BY bin"""


EVERY_TICKET = O.COUNTED.replace("FROM tkt WHERE is_network", "FROM tkt")


@query("t_curve", curve_sql(O.COUNTED, "tap"))
def t_curve(s, d):
    return curve_rows(R.rate_curve(counted(s, d), "tap"))


@query("t_curve_snr", curve_sql(O.COUNTED, "snr"))
def t_curve_snr(s, d):
    """Every value of a continuous metric is a bin of its own: as many bins as records, dealt by range."""
    return curve_rows(R.rate_curve(counted(s, d), "snr"))


@query("t_curve_bins", binned_sql(O.COUNTED, "snr", 20))
def t_curve_bins(s, d):
    return curve_rows(R.rate_curve(counted(s, d), "snr", 20, exact_edges=True))


@query("t_curve_all_tickets", binned_sql(EVERY_TICKET, "snr", 20))
def t_curve_all_tickets(s, d):
    return curve_rows(R.rate_curve(R.count_tickets(held(s, d), A.tickets(s, d)), "snr", 20, exact_edges=True))


@query("t_curve_long", f"""WITH {O.LONG}, overall AS (SELECT sum(tickets) / sum(hours) AS b FROM counted)
SELECT round(l_quantity, 6) AS lo, sum(tickets)::BIGINT AS tickets, round(sum(hours), 2) AS hours, round(sum(tickets) / sum(hours) / any_value(b), 6) AS rate_over_base FROM counted, overall GROUP BY l_quantity""")
def t_curve_long(s, d):
    """The rate curve of the long series: a ticket belongs to the record in force at its day."""
    timed = R.held_intervals(A.supply_telemetry(s, d), A.SUPPLY_END, order=A.SUPPLY_ORDER)
    curve = R.rate_curve(R.count_tickets(timed, A.supply_tickets(s, d)), "l_quantity")
    return curve.select(*rounded("lo"), "tickets", F.round("hours", 2).alias("hours"), *rounded("rate_over_base"))


# Thresholds


def cut_row(out: DataFrame) -> DataFrame:
    return out.select(*rounded("low", "high"), "k_abn", F.round("h_abn", 4).alias("h_abn"), "k_norm", F.round("h_norm", 4).alias("h_norm"), *rounded("trr"))


@query("t_cut_below", O.cut_scan("snr", "below", 50))
def t_cut_below(s, d):
    return cut_row(T.search_threshold(counted(s, d), "snr", "below", 50, min_tickets=GUARD))


@query("t_cut_above", O.cut_scan("unerrored", "above", 50))
def t_cut_above(s, d):
    return cut_row(T.search_threshold(counted(s, d), "unerrored", "above", 50, min_tickets=GUARD))


@query("t_cut_band", O.band_scan("snr", 20))
def t_cut_band(s, d):
    return cut_row(T.search_band(counted(s, d), "snr", 20, min_tickets=GUARD))


@query("t_cut_symmetric", f"""WITH {O.COUNTED}, m AS (SELECT avg(snr) AS m, stddev_pop(snr) AS s FROM counted), w(k) AS (VALUES (1.0::DOUBLE), (1.5), (2.0), (2.5), (3.0)), o AS (SELECT m - k * s AS low, m + k * s AS high FROM m, w)
SELECT round(low, 6) AS low, round(high, 6) AS high, coalesce(sum(tickets) FILTER (WHERE snr < low OR snr > high), 0)::BIGINT AS k_abn, coalesce(sum(tickets) FILTER (WHERE NOT (snr < low OR snr > high)), 0)::BIGINT AS k_norm FROM counted, o GROUP BY low, high""")
def t_cut_symmetric(s, d):
    return T.symmetric_band(counted(s, d), "snr").select(*rounded("low", "high"), "k_abn", "k_norm")


@query("t_trr", f"""WITH {O.COUNTED}, s AS (SELECT sum(tickets) FILTER (WHERE snr < 29) AS ka, sum(hours) FILTER (WHERE snr < 29) AS ha, sum(tickets) FILTER (WHERE snr >= 29) AS kn, sum(hours) FILTER (WHERE snr >= 29) AS hn FROM counted)
SELECT ka::BIGINT AS k_abn, round(ha, 4) AS h_abn, kn::BIGINT AS k_norm, round(hn, 4) AS h_norm, round((ka / ha) / (kn / hn), 6) AS trr FROM s""")
def t_trr(s, d):
    return R.trr(counted(s, d), F.col("snr") < 29).select("k_abn", F.round("h_abn", 4).alias("h_abn"), "k_norm", F.round("h_norm", 4).alias("h_norm"), *rounded("trr"))


@query("t_shape", """WITH m AS (SELECT avg(l_quantity) AS m, stddev_pop(l_quantity) AS s FROM lineitem) SELECT round(avg(power((l_quantity - m) / s, 3)), 6) AS skewness, round(avg(power((l_quantity - m) / s, 4)) - 3, 6) AS kurtosis,
 abs(avg(power((l_quantity - m) / s, 3))) < 1 AND abs(avg(power((l_quantity - m) / s, 4)) - 3) < 1 AS "normal" FROM lineitem, m""")
def t_shape(s, d):
    return T.looks_normal(read_table(s, d, "lineitem"), "l_quantity").select(*rounded("skewness", "kurtosis"), "normal")


@query("t_model", """WITH g AS (SELECT n_nationkey::DOUBLE AS fp, n_regionkey::DOUBLE AS fn FROM nation)
SELECT fp, fn, round(((fp + 5 * 10) / (10 + fp)) / ((100 + 5 * fn) / (100 + fn)), 6) AS ratio, 5.0::DOUBLE AS limit_ratio,
 round((-40 / power(10 + fp, 2)) / ((100 + 5 * fn) / (100 + fn)), 8) AS by_fp, round(-((fp + 50) / (10 + fp)) * (400 / power(100 + fn, 2)) / power((100 + 5 * fn) / (100 + fn), 2), 8) AS by_fn FROM g""")
def t_model(s, d):
    rows = read_table(s, d, "nation").select(F.col("n_nationkey").cast("double").alias("fp"), F.col("n_regionkey").cast("double").alias("fn"))
    args = F.lit(1.0), F.lit(4.0), F.lit(100.0), F.col("fp"), F.col("fn"), F.lit(10.0)
    by_fp, by_fn = C.rate_model_slopes(*args)
    return rows.select("fp", "fn", F.round(C.rate_model(*args), 6).alias("ratio"), C.rate_model_limit(F.lit(1.0), F.lit(4.0)).alias("limit_ratio"), F.round(by_fp, 8).alias("by_fp"), F.round(by_fn, 8).alias("by_fn"))


# The search over all 333 features of the training days, and the selection


def score_rows(out: DataFrame) -> DataFrame:
    return out.select("feature", "metric", "model", "param", "direction", *rounded("low", "high"), "k_abn", F.round("h_abn", 4).alias("h_abn"), "k_norm", F.round("h_norm", 4).alias("h_norm"), *rounded("trr"))


@query("t_search_all", f"WITH RECURSIVE {O.SEARCHED} SELECT {O.SCORE_ROWS} FROM best")
def t_search_all(s, d):
    return score_rows(train_scores(s, d))


@query("s_representatives", f"WITH RECURSIVE {O.SEARCHED} SELECT {O.SCORE_ROWS} FROM represented")
def s_representatives(s, d):
    return score_rows(S.pick_representatives(train_scores(s, d)))


@query("s_top_models", f"WITH RECURSIVE {O.SEARCHED} SELECT {O.SCORE_ROWS} FROM top_models")
def s_top_models(s, d):
    return score_rows(S.pick_top_models(S.pick_representatives(train_scores(s, d))))


@query("q_top_features", f"WITH RECURSIVE {O.DETECTED} SELECT {O.SCORE_ROWS} FROM chosen")
def q_top_features(s, d):
    """The five features that the detector keeps, with their cuts."""
    return score_rows(S.pick_features(train_scores(s, d), O.KEPT))


@query("s_pick", """WITH s AS (SELECT l_returnflag AS metric, l_linestatus AS model, l_linenumber AS param, l_returnflag || '-' || l_linestatus || '-' || l_linenumber AS feature, round(avg(l_extendedprice), 4) AS trr FROM lineitem GROUP BY ALL),
a AS (SELECT * FROM s QUALIFY row_number() OVER (PARTITION BY metric, model ORDER BY trr DESC, feature) = 1), b AS (SELECT * FROM a QUALIFY row_number() OVER (PARTITION BY metric ORDER BY trr DESC, feature) <= 2)
SELECT feature, trr FROM b ORDER BY trr DESC, feature LIMIT 3""")
def s_pick(s, d):
    """The three stages on a table of scores that has many ties and levels."""
    rows = read_table(s, d, "lineitem").groupBy(F.col("l_returnflag").alias("metric"), F.col("l_linestatus").alias("model"), F.col("l_linenumber").alias("param")).agg(F.round(F.avg("l_extendedprice"), 4).alias("trr"))
    return S.pick_features(rows.withColumn("feature", F.concat_ws("-", "metric", "model", "param")), 3).select("feature", "trr")
