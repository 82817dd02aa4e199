"""Clusters of devices and the fault types that follow from them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import clusters as K
from ..operators import measures as M
from ..operators import rates as R
from ..sources import adapters as A
from ..sources.staging import staged
from . import oracle as O
from .base import END, START, marks, periods, tel, typer, typer_model, types
from .book import query, rounded

METHODS = ("average", "single", "complete", "density")
CUTS = tuple(round(0.1 * i, 1) for i in range(1, 8))
GRID = tuple(round(0.05 * i, 2) for i in range(20))
NODES = 25

MOVED = f"""v AS MATERIALIZED (SELECT (vec_id % {NODES})::INT AS g, vec_id AS item, [x[1]::DOUBLE + CASE WHEN x[2] = label THEN 0.7 ELSE 0 END for x in list_zip(embedding, range(64))] AS u FROM embeddings),
items AS (SELECT g, item FROM v),
sims AS MATERIALIZED (SELECT p.g, p.item AS a, q.item AS b, list_dot_product(p.u, q.u) / sqrt(list_dot_product(p.u, p.u)) / sqrt(list_dot_product(q.u, q.u)) AS sim FROM v p JOIN v q ON p.g = q.g AND p.item < q.item)"""


@query("k_pairs", f"WITH {MOVED} SELECT g AS node, a, b, round(sim, 6) AS similarity FROM sims")
def k_pairs(s, d):
    """Cosine of all pairs of a node, over the planted vectors."""
    return K.pair_similarity(A.vectors(s, d, 0.7, NODES)).select("node", "a", "b", *rounded("similarity"))


@query("k_pairs_distance", f"WITH {MOVED}, w AS (SELECT g, item, [x / sqrt(list_dot_product(u, u)) for x in u] AS u FROM v) SELECT p.g AS node, p.item AS a, q.item AS b, round(1 / (1 + list_distance(p.u, q.u)), 6) AS similarity FROM w p JOIN w q ON p.g = q.g AND p.item < q.item")
def k_pairs_distance(s, d):
    return K.pair_similarity(A.vectors(s, d, 0.7, NODES), "distance").select("node", "a", "b", *rounded("similarity"))


@query("k_periods", f"{O.MARKS},{O.period_vectors(('tx',))} SELECT node, slot, device, len(v)::INT AS n, round(list_sum(v), 6) AS total, round(v[1], 6) AS oldest, round(v[len(v)], 6) AS newest FROM vec")
def k_periods(s, d):
    """The vectors of the anomalous periods: held values of the look-back that ends with the period."""
    t = typer()
    v = K.device_vectors(tel(s, d), "tx", START, END, t.every_hours, periods(s, d), t.period_hours, t.look_back_hours)
    return v.select("node", "slot", "device", F.size("vector").alias("n"), F.round(F.aggregate("vector", F.lit(0.0), lambda a, x: a + x), 6).alias("total"), F.round(F.element_at("vector", 1), 6).alias("oldest"), F.round(F.element_at("vector", -1), 6).alias("newest"))


@query("k_pairs_pearson", f"{O.MARKS},{O.period_vectors(('tx',))} SELECT node, slot, a, b, round(sim, 6) AS similarity FROM sims")
def k_pairs_pearson(s, d):
    """Pearson correlation, the typer's similarity, of all devices that are anomalous in the same node and period."""
    t = typer()
    v = K.device_vectors(tel(s, d), "tx", START, END, t.every_hours, periods(s, d), t.period_hours, t.look_back_hours)
    return K.pair_similarity(v, "pearson").select("node", "slot", "a", "b", *rounded("similarity"))


def clustered(s, d, method: str) -> DataFrame:
    return K.cluster_devices(A.vectors(s, d, 0.7, NODES), CUTS, method, "cosine").select("device", "cut", "cluster_id", "size")


LABELLED = 'SELECT item AS device, cut, cluster AS cluster_id, size FROM labelled'


@query("k_average", f"WITH RECURSIVE {MOVED},{O.linkage('avg', min(CUTS))},{O.cut(CUTS)} {LABELLED}")
def k_average(s, d):
    return clustered(s, d, "average")


@query("k_single", f"WITH RECURSIVE {MOVED},{O.linkage('max', min(CUTS))},{O.cut(CUTS)} {LABELLED}")
def k_single(s, d):
    return clustered(s, d, "single")


@query("k_complete", f"WITH RECURSIVE {MOVED},{O.linkage('min', min(CUTS))},{O.cut(CUTS)} {LABELLED}")
def k_complete(s, d):
    return clustered(s, d, "complete")


@query("k_density", f"WITH RECURSIVE {MOVED},{O.density(CUTS)} {LABELLED}")
def k_density(s, d):
    return clustered(s, d, "density")


def agreement(found: DataFrame, keys: list[str]) -> DataFrame:
    """RI and ARI of (keys, node, cluster_id, label) for each value of the keys, from contingency tables."""
    pairs = lambda c: F.col(c) * (F.col(c) - 1) / 2
    n = F.sum("n").alias("n")
    cells = found.groupBy(*keys, "node", "cluster_id", "label").agg(F.count(F.lit(1)).alias("n"))
    both = cells.groupBy(*keys).agg(F.sum(pairs("n")).alias("p_ab"), F.sum("n").alias("items"))
    one = cells.groupBy(*keys, "node", "cluster_id").agg(n).groupBy(*keys).agg(F.sum(pairs("n")).alias("p_a"))
    two = cells.groupBy(*keys, "label").agg(n).groupBy(*keys).agg(F.sum(pairs("n")).alias("p_b"))
    total = F.col("items") * (F.col("items") - 1) / 2
    expected = F.try_divide(F.col("p_a") * F.col("p_b"), total)
    ri = F.try_divide(total + 2 * F.col("p_ab") - F.col("p_a") - F.col("p_b"), total)
    ari = F.try_divide(F.col("p_ab") - expected, (F.col("p_a") + F.col("p_b")) / 2 - expected)
    return both.join(one, keys).join(two, keys).select(*keys, F.round(ri, 4).alias("ri"), F.round(ari, 4).alias("ari"))


@query("k_agreement")
def k_agreement(s, d):
    """Agreement of the four algorithms with a labelled set of 16 shared faults in four nodes and lone devices (one in seven),
    at every cut and for every strength of the plant."""
    out = None
    for alpha in (0.0, 0.5, 0.7, 1.0):
        vectors = A.grouped_vectors(s, d, alpha)
        truth = vectors.select("device", "label")
        for method in METHODS:
            found = K.cluster_devices(vectors.drop("label"), CUTS, method, "cosine").join(truth, "device").withColumns({"alpha": F.lit(alpha), "method": F.lit(method)})
            out = found if out is None else out.unionByName(found)
    return agreement(out, ["alpha", "method", "cut"])


@query("k_corr", f"WITH {O.BASE} SELECT 'snr' AS a, 'tx' AS b, round(corr(snr, tx), 6) AS corr FROM tel UNION ALL SELECT 'snr', 'rx', round(corr(snr, rx), 6) FROM tel UNION ALL SELECT 'tx', 'rx', round(corr(tx, rx), 6) FROM tel")
def k_corr(s, d):
    return K.metric_correlation(tel(s, d), ("snr", "tx", "rx")).select("a", "b", *rounded("corr"))


# Types of the periods that the detector finds anomalous


def typed(s, d, metric: str, cuts=GRID) -> DataFrame:
    return typer().model({}).types(tel(s, d), periods(s, d), metric, cuts)


ONE = f"{O.MARKS},{O.period_types(('tx',), GRID)}"
BOTH = f"{O.MARKS},{O.period_types(('snr', 'tx'), GRID)}{O.TYPED_TIME}"


@query("k_types", f"{ONE} SELECT node, slot, device, cut, cluster AS cluster_id, size, fault_type FROM typed")
def k_types(s, d):
    """Type of each anomalous device period by transmit power, at every cut."""
    return typed(s, d, "tx").select("node", "slot", "device", "cut", "cluster_id", "size", "fault_type")


@query("k_cuts", f"{ONE} SELECT cut, count(DISTINCT (node, slot, cluster)) AS clusters, count(*) FILTER (WHERE size = 1) AS singles, max(size) AS largest FROM typed GROUP BY cut")
def k_cuts(s, d):
    """How the cut splits and merges."""
    return K.cut_sensitivity(typed(s, d, "tx"))


@query("k_trr", f"{BOTH} SELECT metric, cut, k_mm::BIGINT AS k_mm, round(h_m, 4) AS h_m, k_ms::BIGINT AS k_ms, round(h_s, 4) AS h_s, round(CASE WHEN k_mm >= 5 THEN (k_mm / nullif(h_m, 0)) / nullif(k_ms / nullif(h_s, 0), 0) END, 6) AS trr_m FROM rated_types")
def k_trr(s, d):
    """The maintenance rate ratio of every cut, for each of the typer's metrics, over the periods diagnosed."""
    t, seen = typer(), staged(marks(s, d), "marks")  # read several times for each metric
    scores = [t.scores(seen, A.tickets(s, d), m).withColumn("metric", F.lit(m)) for m in t.metrics]
    return reduce(DataFrame.unionByName, scores).select("metric", "cut", "k_mm", F.round("h_m", 4).alias("h_m"), "k_ms", F.round("h_s", 4).alias("h_s"), *rounded("trr_m"))


@query("k_fitted_cuts", f"{BOTH}{O.FITTED_TYPES} SELECT metric, cut FROM chosen_cut")
def k_fitted_cuts(s, d):
    """The cut of each metric that the typer keeps."""
    return s.createDataFrame(sorted(typer_model(s, d).cuts.items()), "metric string, cut double")


@query("k_combined", f"{BOTH}{O.FITTED_TYPES} SELECT device, slot, fault_type FROM fitted_types")
def k_combined(s, d):
    """Both metrics' types together: the type of each anomalous device period."""
    return types(s, d).select("device", "slot", "fault_type")


@query("k_combined_all", f"""{BOTH}{O.FITTED_TYPES} SELECT device, slot, CASE WHEN bool_and(fault_type = 'maintenance') THEN 'maintenance' ELSE 'service' END AS fault_type FROM typed JOIN chosen_cut USING (metric, cut) GROUP BY device, slot""")
def k_combined_all(s, d):
    """Maintenance only where both metrics say so."""
    fitted = typer_model(s, d)
    one, two = [fitted.types(tel(s, d), periods(s, d), m, [cut]).select("device", "slot", "fault_type") for m, cut in fitted.cuts.items()]
    return K.combine_types(one, two, "all", ("device", "slot"))


@query("q_lift", f"""{BOTH}{O.FITTED_TYPES},
kinds AS (SELECT c.*, CASE WHEN m.marked THEN t.fault_type END AS fault_type FROM held c JOIN marks m USING (rec_id) LEFT JOIN fitted_types t ON t.device = c.device AND t.slot = {O.SLOT.format('c.ts')}),
told AS (SELECT is_maintenance, (SELECT arg_max(h.rec_id, (h.ts, h.rec_id)) FROM held h WHERE h.account = t.account AND h.ts <= t.created) AS rec_id FROM net t),
sums AS (SELECT k.*, (SELECT count(*) FROM told w WHERE w.rec_id = k.rec_id AND is_maintenance) AS km, (SELECT count(*) FROM told w WHERE w.rec_id = k.rec_id AND NOT is_maintenance) AS ks FROM kinds k),
whole AS (SELECT sum(km) / sum(hours) AS rm, sum(ks) / sum(hours) AS rs FROM sums)
SELECT fault_type, round(sum(hours), 4) AS hours, sum(km)::BIGINT AS km, sum(ks)::BIGINT AS ks, round(CASE WHEN fault_type = 'maintenance' THEN sum(km) / sum(hours) / any_value(rm) ELSE sum(ks) / sum(hours) / any_value(rs) END, 6) AS lift
FROM sums, whole WHERE fault_type IS NOT NULL GROUP BY fault_type""")
def q_lift(s, d):
    """Rate of each kind of ticket in time diagnosed as the matching fault type, over its overall rate."""
    from ..functions.columns import period_of

    rows = marks(s, d).withColumn("slot", period_of("ts", START, typer().period_hours))
    tickets = A.tickets(s, d).where("is_network")
    both = R.count_tickets(rows, tickets.where("is_maintenance"), name="k_maintenance")
    both = R.count_tickets(both, tickets.where("not is_maintenance"), name="k_service")
    named = both.join(types(s, d), ["device", "slot"], "left").withColumn("fault_type", F.when(F.col("marked"), F.col("fault_type")))
    return M.typed_rate_lift(named).select("fault_type", F.round("hours", 4).alias("hours"), "km", "ks", *rounded("lift"))


@query("q_type_truth", f"""{BOTH}{O.FITTED_TYPES}, plants AS (SELECT device, {O.SLOT.format('ts')} AS slot, bool_or(maint) AS shared, bool_or(serv) AS lone FROM tel GROUP BY ALL)
SELECT CASE WHEN shared THEN 'shared' WHEN lone THEN 'lone' ELSE 'none' END AS planted, fault_type, count(*) AS n FROM fitted_types JOIN plants USING (device, slot) GROUP BY ALL""")
def q_type_truth(s, d):
    """The types against the plant: scoring only, nothing is fitted to it."""
    from ..functions.columns import period_of

    truth = tel(s, d).groupBy("device", period_of("ts", START, typer().period_hours).alias("slot")).agg(F.max("maint").alias("shared"), F.max("serv").alias("lone"))
    kind = F.when(F.col("shared"), "shared").when(F.col("lone"), "lone").otherwise("none").alias("planted")
    return types(s, d).join(truth, ["device", "slot"]).groupBy(kind, "fault_type").agg(F.count(F.lit(1)).alias("n"))
