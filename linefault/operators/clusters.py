"""Grouping anomalous devices by similar behaviour, and what the groups say about fault types.

Devices are compared only within a node and slot, so a group is small and its merging runs in one Python
task; groups run in parallel. Agglomeration keeps each row's best partner and so costs about m**2. One merge tree
yields the clusters at every cut of a grid.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import period_of, ratio
from .features import resample_hold

LINKAGES = ("average", "single", "complete")
SIMILARITIES = ("pearson", "cosine", "distance")
#: Beyond so many devices, or clusters, a node's similarities are computed in blocks of rows; results don't depend on it.
MOST_IN_GROUP = 4000
#: Similarities that one block of rows holds.
BLOCK_CELLS = 2**22
#: Pairs of a node that are listed for one cut; more are searched block by block.
MOST_EDGES = 2**20


def similarity_matrix(vectors: np.ndarray, kind: str = "pearson") -> np.ndarray:
    """Pairwise similarity; a constant (or zero) vector is similar to nothing but itself."""
    x = np.asarray(vectors, float)
    if kind == "distance":
        squares = (x * x).sum(axis=1)
        return 1.0 / (1.0 + np.sqrt(np.maximum(squares[:, None] + squares[None, :] - 2 * x @ x.T, 0.0)))
    if kind == "pearson":
        x = x - x.mean(axis=1, keepdims=True)
    norm = np.sqrt((x * x).sum(axis=1))
    unit = np.where(norm[:, None] > 1e-12, x / np.where(norm > 1e-12, norm, 1.0)[:, None], 0.0)
    out = unit @ unit.T
    np.fill_diagonal(out, 1.0)
    return out


def prepared(vectors: np.ndarray, kind: str = "pearson"):
    """The vectors as rows x, and a function that gives the similarities of some of these rows with others; the whole matrix is never
    held. A row's similarity with itself is left as computed."""
    x = np.asarray(vectors, float)
    if kind == "distance":

        def away(a: np.ndarray, b: np.ndarray) -> np.ndarray:
            return 1.0 / (1.0 + np.sqrt(np.maximum((a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1)[None, :] - 2 * a @ b.T, 0.0)))

        return x, away
    if kind == "pearson":
        x = x - x.mean(axis=1, keepdims=True)
    norm = np.sqrt((x * x).sum(axis=1))
    return np.where(norm[:, None] > 1e-12, x / np.where(norm > 1e-12, norm, 1.0)[:, None], 0.0), lambda a, b: a @ b.T


def neighbours(x: np.ndarray, similar, cuts: Sequence[float]) -> tuple[np.ndarray, list]:
    """From one pass over all pairs: how many items reach each item at each cut (itself included), and the pairs at each cut, or None
    where they are more than MOST_EDGES."""
    n, step = len(x), max(1, BLOCK_CELLS // max(1, len(x)))
    count, edges = np.zeros((len(cuts), n), int), [[] for _ in cuts]
    for at in range(0, n, step):
        s = similar(x[at : at + step], x)
        s[np.arange(len(s)), np.arange(at, at + len(s))] = 1.0
        for k, cut in enumerate(cuts):
            near = s >= cut
            count[k, at : at + step] = np.count_nonzero(near, axis=1)
            if edges[k] is not None:
                edges[k] = [*edges[k], np.flatnonzero(near) + at * n] if count[k].sum() <= MOST_EDGES else None
    return count, [None if e is None else np.divmod(np.concatenate([*e, np.zeros(0, int)]), n) for e in edges]


def reach(x: np.ndarray, similar, cut: float, core: np.ndarray, count: np.ndarray) -> np.ndarray:
    """For each item the first core from which it is reached over cores at the cut, or -1. Items that are reached leave the columns
    of later blocks. count: how many items reach each item, itself included."""
    n = len(x)
    label, left, held, free = np.full(n, -1), np.arange(n), x, n
    for i in np.flatnonzero(core):
        if label[i] >= 0:
            continue
        label[i], free = i, free - 1
        todo = np.array([i] if count[i] > 1 else [], int)
        while len(todo) and free:
            step = max(1, BLOCK_CELLS // len(left))
            now, todo = todo[:step], todo[step:]
            new = left[(similar(x[now], held) >= cut).any(axis=0)]
            new = new[label[new] < 0]
            label[new], free = i, free - len(new)
            todo = np.concatenate([todo, new[core[new]]])
            if free < 0.8 * len(left):
                left = left[label[left] < 0]
                held = x[left]
    return label


def reach_by_edges(n: int, edges: tuple[np.ndarray, np.ndarray], core: np.ndarray) -> np.ndarray:
    """What `reach` gives, from all pairs at the cut in both orders."""
    a, b = edges
    inner = core[a] & core[b]
    label = np.arange(n)
    while True:
        low = label.copy()
        np.minimum.at(low, a[inner], label[b[inner]])
        low = low[low]
        if (low == label).all():
            break
        label = low
    first = np.full(n, n)
    np.minimum.at(first, a[core[b]], label[b[core[b]]])
    return np.where(core, label, np.where(first < n, first, -1))


def merges_by_rows(x: np.ndarray, similar, linkage: str, floor: float, means: bool, most: int) -> list[tuple[int, int, float]]:
    """The merges of average or complete linkage down to the floor, highest first, in memory for blocks of rows and for a matrix
    of `most` clusters.

    Two clusters that are each other's most similar one merge in any order of merging, so all such pairs merge at once, round
    by round. A cluster's best partner is sought again only after that partner has merged, and its old similarity bounds the new
    one: where rounds find few pairs, the highest bounds are sought first. Clusters below the floor leave. Once `most` clusters
    are left, these are merged on their matrix. means: the similarity is a product of vectors, so that of two clusters
    on average is the product of their mean vectors; otherwise it is folded from their members.
    """
    n = len(x)
    name, size, low = np.arange(n), np.ones(n, int), np.full(n, np.inf)
    best, value, fresh = np.zeros(n, int), np.full(n, np.inf), np.zeros(n, bool)
    owner, order = np.arange(n), np.arange(n)  # the items in x and their clusters, unless by means
    column = np.arange(n)  # the clusters as they stand in a block: by falling size, unless by means
    held, fold, out, tries = x.copy() if means else x, np.add if linkage == "average" else np.minimum, [], n

    def layers(many: np.ndarray) -> np.ndarray:
        """How many clusters have a first, a second, ... member."""
        return len(many) - np.searchsorted(np.sort(many), np.arange(many.max()), "right")

    def folded(part: np.ndarray, widths: np.ndarray) -> np.ndarray:
        """One row a cluster, from all first members, then all second ones, and so on; clusters are by falling size."""
        at = widths[0]
        for w in widths[1:]:
            fold(part[:w], part[at : at + w], out=part[:w])
            at += w
        return part[: widths[0]]

    def level(q: np.ndarray):
        """Blocks of the similarities of clusters q with all clusters in the order of `column`; with themselves -inf."""
        step, place = max(1, BLOCK_CELLS // len(held)), np.empty(len(column), int)
        place[column] = np.arange(len(column))
        if not means:
            widths = layers(size)
            offset = np.cumsum(widths) - widths
            q = q[np.argsort(-size[q], kind="stable")]
        total, at = np.cumsum(size[q]) if not means else np.arange(1, len(q) + 1), 0
        while at < len(q):
            to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + step, "right")))
            now = q[at:to]
            if means:
                s = held[now] @ held.T
            else:
                own = layers(size[now])
                items, s = np.concatenate([offset[j] + place[now[:w]] for j, w in enumerate(own)]), None
                for k in range(0, len(items), step):  # more than one block only for a cluster that is larger than one
                    part = similar(held[items[k : k + step]], held)
                    part = fold.reduce(part, axis=0, keepdims=True) if len(now) == 1 else folded(part, own)
                    s = part if s is None else fold(s, part)
                s = folded(s.T, widths).T
                if linkage == "average":
                    s = s / (size[now][:, None] * size[column][None, :])
            s[np.arange(len(now)), place[now]] = -np.inf
            yield now, s
            at = to

    while len(name) > max(1, most):
        q = np.flatnonzero(~fresh)
        if len(q) > tries:
            q = np.sort(q[np.argpartition(-value[q], tries)[:tries]])
        for now, s in level(q):
            most_like = s.argmax(axis=1)
            best[now], value[now] = column[most_like], s[np.arange(len(now)), most_like]
            if not means:  # of equals the first by name, as the columns are by size
                equal = s == value[now][:, None]
                for i in np.flatnonzero(np.count_nonzero(equal, axis=1) > 1):
                    best[now[i]] = column[equal[i]].min()
        fresh[q] = True
        every = np.arange(len(name))
        a = np.flatnonzero(fresh & fresh[best] & (best[best] == every) & (every < best) & (value >= floor))
        b, height = best[a], value[a]
        if not len(a) and fresh.all() and value.max() >= floor:  # a ring of equals
            i = int(value.argmax())
            a, b, height = np.array([min(i, best[i])]), np.array([max(i, best[i])]), value[[i]]
        tries = max(64, 4 * len(a)) if len(a) else 2 * tries
        height = np.minimum(height, np.minimum(low[a], low[b]))
        out += zip(name[a].tolist(), name[b].tolist(), height.tolist(), strict=True)
        low[a] = height
        if means:
            held[a] = (size[a][:, None] * held[a] + size[b][:, None] * held[b]) / (size[a] + size[b])[:, None]
        size[a] += size[b]
        keep, moved, target = value >= floor, np.zeros(len(name), bool), every.copy()
        keep[b], moved[a], moved[b], target[b] = False, True, True, a
        fresh &= ~moved & ~moved[best] & keep[best]
        place = np.cumsum(keep) - 1
        if not means:
            stay = keep[target[owner]]
            owner, order = place[target[owner[stay]]], order[stay]
            by = np.argsort(owner, kind="stable")
            owner, order = owner[by], order[by]
            many = np.bincount(owner, minlength=int(keep.sum()))
            column = np.argsort(-many, kind="stable")
            rank, spot = np.arange(len(owner)) - np.repeat(np.cumsum(many) - many, many), np.empty(len(many), int)
            spot[column] = np.arange(len(many))
            held = x[order[np.lexsort((spot[owner], rank))]]
        else:
            held, column = held[keep], column[: int(keep.sum())]
        best = place[best]
        name, size, low, best, value, fresh = (v[keep] for v in (name, size, low, best, value, fresh))
    if len(name) > 1:
        whole = np.empty((len(name), len(name)))
        for now, s in level(np.arange(len(name))):
            whole[now[:, None], column[None, :]] = s
        for a, b, s in merge_tree(whole, linkage, floor, True, size):
            low[a] = min(s, low[a], low[b])
            out.append((int(name[a]), int(name[b]), float(low[a])))
    return sorted(out, key=lambda m: -m[2])


def labels_by_rows(vectors: np.ndarray, kind: str, method: str, cuts: Sequence[float], min_points: int, noise: str, most: int = MOST_IN_GROUP):
    """The labels at each cut, as from the whole matrix, for nodes of many devices.

    One block of rows is held at a time. In average and complete linkage two clusters that merge at or above the lowest cut hold a pair
    at or above it, so no cluster leaves a component of these pairs; each component is merged alone, on its own matrix up to
    `most` items.
    """
    n = len(vectors)
    (x, similar), every = prepared(vectors, kind), np.ones(n, bool)
    if method in ("single", "density"):
        count, edges = neighbours(x, similar, cuts)
        for k, cut in enumerate(cuts):
            core = every if method == "single" else count[k] >= min_points
            label = reach(x, similar, cut, core, count[k]) if edges[k] is None else reach_by_edges(n, edges[k], core)
            lone = np.flatnonzero(label < 0)
            label[lone] = lone if noise == "single" or not len(lone) else lone[0]
            yield label
        return
    part = reach(x, similar, min(cuts), every, np.full(n, 2))
    order = np.argsort(part, kind="stable")
    trees = []
    for item in np.split(order, np.flatnonzero(np.diff(part[order])) + 1):
        if len(item) > most:
            trees.append((item, merges_by_rows(x[item], similar, method, min(cuts), method == "average" and kind != "distance", most)))
        elif len(item) > 1:
            trees.append((item, merge_tree(similarity_matrix(vectors[item], kind), method, min(cuts), True)))
    for cut in cuts:
        label = np.arange(n)
        for item, merges in trees:
            label[item] = item[cut_tree(len(item), merges, cut)]
        yield label


def merge_tree(similar: np.ndarray, linkage: str = "average", floor: float = -np.inf, own: bool = False, sizes: np.ndarray | None = None) -> list[tuple[int, int, float]]:
    """Merges (kept, absorbed, similarity) in order, until no two clusters reach the floor.

    Of equally similar pairs the one with the smallest members goes first. With `own` the matrix is used up, not copied. sizes: of
    the clusters that the rows stand for, else 1 each.
    """
    n = len(similar)
    s = similar if own else similar.astype(float).copy()
    np.fill_diagonal(s, -np.inf)
    size, alive = np.ones(n) if sizes is None else sizes.astype(float), np.ones(n, bool)
    best = s.argmax(axis=1) if n else np.zeros(0, int)
    value = s[np.arange(n), best] if n else np.zeros(0)
    out = []
    for _ in range(n - 1):
        a = int(np.argmax(value))
        if not value[a] >= floor or value[a] == -np.inf:
            break
        b = int(best[a])
        a, b = min(a, b), max(a, b)
        out.append((a, b, float(s[a, b])))
        if linkage == "average":
            row = (size[a] * s[a] + size[b] * s[b]) / (size[a] + size[b])
        else:
            row = np.maximum(s[a], s[b]) if linkage == "single" else np.minimum(s[a], s[b])
        row[~alive] = -np.inf
        row[[a, b]] = -np.inf
        s[a], s[:, a] = row, row
        s[b], s[:, b] = -np.inf, -np.inf
        size[a] += size[b]
        alive[b] = False
        value[b] = -np.inf
        stale = np.flatnonzero(alive & ((best == a) | (best == b)))
        better = np.flatnonzero(alive & (row > value))
        value[better], best[better] = row[better], a
        for i in {*stale.tolist(), a}:
            best[i] = int(s[i].argmax())
            value[i] = s[i, best[i]]
    return out


def cut_tree(n: int, merges: Sequence[tuple[int, int, float]], cut: float) -> np.ndarray:
    """Cluster of each item, named by its smallest member: merging stops at the first similarity below the cut."""
    label = np.arange(n)
    for a, b, s in merges:
        if s < cut:
            break
        label[b] = a  # of two clusters the one with the smallest member is kept
    while True:
        up = label[label]
        if (up == label).all():
            return label
        label = up


def density_labels(similar: np.ndarray, cut: float, min_points: int = 4, noise: str = "single") -> np.ndarray:
    """Density clusters: cores have min_points neighbours (themselves included) at the cut; borders join the
    first core cluster in order. noise: each alone, or 'group' for one cluster of all."""
    n = len(similar)
    near = similar >= cut
    core = near.sum(axis=1) >= min_points
    label = np.full(n, -1)
    for i in range(n):
        if core[i] and label[i] < 0:
            label[i] = i
            todo = [i]
            while todo:
                for j in np.flatnonzero(near[todo.pop()] & (label < 0)):
                    label[j] = i
                    if core[j]:
                        todo.append(int(j))
    lone = np.flatnonzero(label < 0)
    label[lone] = lone if noise == "single" or not len(lone) else lone[0]
    return label


def anomalous_periods(marks: DataFrame, start: str, period_hours: int) -> DataFrame:
    """(device, node, slot): the periods in which a device has a marked record."""
    return marks.where("marked").select("device", "node", period_of("ts", start, period_hours).alias("slot")).distinct()


def device_vectors(df: DataFrame, metric: str, start: str, end: str, every_hours: int = 12, devices: DataFrame | None = None, period_hours: int | None = None, look_back_hours: int | None = None) -> DataFrame:
    """(node, slot, device, vector): the metric held on a regular grid, as one vector.

    Without period_hours there is one slot, 0, with the grid over [start, end). With it `devices` has (device, slot), and a
    slot's vector is the grid of the look_back_hours (the period itself unless given) that end with the period. Grid points
    before a device's first record take its first value. All vectors of a slot are of one length.
    """
    rows = df if devices is None else df.join(devices.select("device").distinct(), "device", "left_semi")
    grid = resample_hold(rows, metric, start, end, every_hours, keys=("device", "node"))
    along = Window.partitionBy("device", "node").orderBy("slot").rowsBetween(0, Window.unboundedFollowing)
    full = grid.select("node", "device", F.col("slot").alias("at"), F.coalesce("value", F.first("value", ignorenulls=True).over(along), F.lit(0.0)).alias("value"))
    if period_hours is None:
        placed = full.withColumn("slot", F.lit(0))
    else:
        last = period_of("at", start, period_hours)
        reach = F.lit(max(look_back_hours or period_hours, period_hours) - period_hours)
        until = period_of(F.col("at") + F.make_dt_interval(hours=reach), start, period_hours)
        wide = full.withColumn("slot", F.explode(F.sequence(last, until)))
        placed = wide.join(devices.select("device", "slot").distinct(), ["device", "slot"], "left_semi")
    packed = placed.groupBy("node", "slot", "device").agg(F.array_sort(F.collect_list(F.struct("at", "value"))).alias("points"))
    return packed.select("node", "slot", "device", F.transform("points", lambda p: p["value"]).alias("vector"))


def pair_similarity(vectors: DataFrame, kind: str = "cosine") -> DataFrame:
    """(node, slot, a, b, similarity) of all pairs of a node and slot in SQL; for small nodes and as a check."""
    add = lambda acc, v: acc + v
    total = lambda x: F.aggregate(x, F.lit(0.0), add)
    dot = lambda x, y: total(F.zip_with(x, y, lambda p, q: p * q))
    own = F.col("vector")
    if kind == "pearson":
        mean = total(own) / F.size(own)
        own = F.transform(own, lambda v: v - mean)
    x = vectors.select("node", "slot", "device", own.alias("v"))
    a = x.select("node", "slot", F.col("device").alias("a"), F.col("v").alias("va"))
    b = x.select("node", "slot", F.col("device").alias("b"), F.col("v").alias("vb"))
    pairs = a.join(b, ["node", "slot"]).where("a < b")
    if kind == "distance":
        away = F.sqrt(total(F.zip_with("va", "vb", lambda p, q: (p - q) * (p - q))))
        value = F.lit(1.0) / (F.lit(1.0) + away)
    else:
        size = lambda v: F.sqrt(dot(F.col(v), F.col(v)))
        value = F.when((size("va") > 1e-12) & (size("vb") > 1e-12), dot(F.col("va"), F.col("vb")) / (size("va") * size("vb"))).otherwise(0.0)
    return pairs.select("node", "slot", "a", "b", value.alias("similarity"))


def cluster_devices(vectors: DataFrame, cuts: Sequence[float], method: str = "average", similarity: str = "pearson", min_points: int = 4, noise: str = "single", most: int = MOST_IN_GROUP) -> DataFrame:
    """(node, slot, device, cut, cluster_id, size) at every cut; cluster_id is the smallest device of the cluster.

    method: one of LINKAGES, or 'density'. Nodes larger than `most` give the same clusters without their whole matrix.
    """
    if method not in (*LINKAGES, "density") or similarity not in SIMILARITIES:
        raise ValueError("unknown method or similarity")
    wanted = [float(c) for c in cuts]

    def run(part: pd.DataFrame) -> pd.DataFrame:
        out = []
        rows = part.sort_values("device")
        device, x = rows["device"].to_numpy(), np.stack(rows["vector"].to_list())
        if len(device) > most:
            labels = labels_by_rows(x, similarity, method, wanted, min_points, noise, most)
        else:
            s = similarity_matrix(x, similarity)
            merges = merge_tree(s, method, min(wanted)) if method != "density" else []
            labels = (cut_tree(len(device), merges, c) if method != "density" else density_labels(s, c, min_points, noise) for c in wanted)
        for cut, label in zip(wanted, labels, strict=True):
            count = np.bincount(label, minlength=len(device))
            out.append(pd.DataFrame({"node": rows["node"].to_numpy(), "slot": rows["slot"].to_numpy(), "device": device, "cut": cut, "cluster_id": device[label], "size": count[label]}))
        return pd.concat(out) if out else pd.DataFrame(columns=["node", "slot", "device", "cut", "cluster_id", "size"])

    return vectors.groupBy("node", "slot").applyInPandas(run, "node int, slot int, device long, cut double, cluster_id long, size long")


def type_faults(clusters: DataFrame, min_group: int = 2, healthy: DataFrame | None = None) -> DataFrame:
    """clusters with fault_type: maintenance for groups of at least min_group, else service; devices in
    `healthy` get none."""
    typed = clusters.withColumn("fault_type", F.when(F.col("size") >= min_group, "maintenance").otherwise("service"))
    if healthy is None:
        return typed
    well = healthy.select("device").distinct().withColumn("well", F.lit(True))
    return typed.join(well, "device", "left").withColumn("fault_type", F.when(F.col("well").isNull(), F.col("fault_type"))).drop("well")


def combine_types(first: DataFrame, second: DataFrame, how: str = "any", keys: Sequence[str] = ("device",)) -> DataFrame:
    """(keys, fault_type) of two features' types: maintenance if any (or with 'all', both) says so."""
    a = first.select(*keys, F.col("fault_type").alias("t1"))
    b = second.select(*keys, F.col("fault_type").alias("t2"))
    joined = a.join(b, list(keys), "full")
    one, two = F.coalesce(F.col("t1") == "maintenance", F.lit(False)), F.coalesce(F.col("t2") == "maintenance", F.lit(False))
    shared = one | two if how == "any" else one & two
    return joined.select(*keys, F.when(shared, "maintenance").when(F.coalesce("t1", "t2").isNotNull(), "service").alias("fault_type"))


def metric_correlation(df: DataFrame, metrics: Sequence[str]) -> DataFrame:
    """(a, b, corr) of all pairs of metrics, one scan: which metrics carry the same information."""
    pairs = [(a, b) for i, a in enumerate(metrics) for b in metrics[i + 1 :]]
    row = df.agg(*[F.corr(a, b).alias(f"{a}|{b}") for a, b in pairs])
    return row.select(F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(f"`{a}|{b}`").alias("corr")) for a, b in pairs])).alias("p")).select("p.*")


def maintenance_ratio(typed: DataFrame, counted: DataFrame, min_tickets: int = 0) -> DataFrame:
    """(cut, k_mm, h_m, k_ms, h_s, trr_m): the rate of maintenance tickets in time diagnosed as maintenance, over their rate
    in time diagnosed as service.

    typed has device, slot, cut and fault_type. counted has the collection periods of impaired records: device, slot,
    tickets (maintenance ones) and hours, backward held. What a device does in other periods is not looked at.
    """
    period = counted.groupBy("device", "slot").agg(F.sum("tickets").alias("k"), F.sum("hours").alias("h"))
    rows = typed.where("fault_type is not null").join(period, ["device", "slot"])
    of = lambda t, c: F.coalesce(F.sum(F.when(F.col("fault_type") == t, F.col(c))), F.lit(0))
    sums = rows.groupBy("cut").agg(of("maintenance", "k").alias("k_mm"), of("maintenance", "h").cast("double").alias("h_m"), of("service", "k").alias("k_ms"), of("service", "h").cast("double").alias("h_s"))
    value = F.try_divide(ratio(F.col("k_mm"), F.col("h_m")), ratio(F.col("k_ms"), F.col("h_s")))
    return sums.withColumn("trr_m", F.when(F.col("k_mm") >= min_tickets, value))


def best_cut(scores: DataFrame) -> DataFrame:
    """The cut with the highest trr_m; of equals the higher."""
    return scores.where("trr_m is not null").orderBy(F.desc(F.round("trr_m", 9)), F.desc("cut")).limit(1)


def cut_sensitivity(clusters: DataFrame) -> DataFrame:
    """(cut, clusters, singles, largest): how a cut splits or merges."""
    by = clusters.select("cut", "node", "slot", "cluster_id", "size").distinct()
    return by.groupBy("cut").agg(F.count(F.lit(1)).alias("clusters"), F.sum((F.col("size") == 1).cast("int")).alias("singles"), F.max("size").alias("largest"))
