import datetime as dt
import itertools

import numpy as np
import pytest

from linefault.operators import clusters as K
from linefault.sources import adapters as A


def naive(s, linkage, cut):
    groups = [[i] for i in range(len(s))]
    fold = {"average": np.mean, "single": np.max, "complete": np.min}[linkage]
    while len(groups) > 1:
        best = max(((fold([s[i, j] for i in a for j in b]), -min(a), -min(b), a, b) for a, b in itertools.combinations(groups, 2)), key=lambda t: t[:3])
        if best[0] < cut:
            break
        groups.remove(best[3])
        groups.remove(best[4])
        groups.append(sorted(best[3] + best[4]))
        groups.sort()
    out = np.empty(len(s), int)
    for g in groups:
        out[g] = min(g)
    return out


@pytest.mark.parametrize("linkage", K.LINKAGES)
@pytest.mark.parametrize("seed", range(4))
def test_linkage_equals_naive(linkage, seed):
    s = K.similarity_matrix(np.random.default_rng(seed).normal(size=(25, 6)), "pearson")
    merges = K.merge_tree(s, linkage, 0.0)
    for cut in (0.1, 0.4, 0.7):
        assert K.cut_tree(25, merges, cut).tolist() == naive(s, linkage, cut).tolist()


@pytest.mark.parametrize("method", [*K.LINKAGES, "density"])
def test_large_node_equals_uncut(spark, method, monkeypatch):
    monkeypatch.setattr(K, "BLOCK_CELLS", 300)
    rng = np.random.default_rng(3)
    x = rng.normal(size=(12, 6))[rng.integers(0, 12, 60)] + rng.normal(size=(60, 6)) * 0.3
    x[7] = 1.0
    for kind in K.SIMILARITIES:
        for noise in ("single", "group"):
            s = K.similarity_matrix(x, kind)
            cuts = (0.3, 0.6, 0.9)
            merges = K.merge_tree(s, method, 0.3) if method != "density" else []
            want = [(K.cut_tree(60, merges, c) if method != "density" else K.density_labels(s, c, 4, noise)).tolist() for c in cuts]
            assert [v.tolist() for v in K.labels_by_rows(x, kind, method, cuts, 4, noise)] == want
    rows = spark.createDataFrame([(0, 0, i, [float(v) for v in r]) for i, r in enumerate(x)], "node int, slot int, device long, vector array<double>")
    found = lambda most: sorted(tuple(r) for r in K.cluster_devices(rows, (0.3, 0.6, 0.9), method, "cosine", most=most).collect())
    assert found(20) == found(100)


@pytest.mark.parametrize("method", ["average", "complete"])
@pytest.mark.parametrize("kind", K.SIMILARITIES)
def test_large_component_without_its_matrix(kind, method, monkeypatch):
    """One component of all items, with copies and vectors that are similar to nothing: no matrix beyond `most`, same clusters."""
    rng = np.random.default_rng(5)
    x = np.abs(rng.normal(size=(12, 8)))[rng.integers(0, 12, 150)] + rng.normal(size=(150, 8)) * 0.4
    x[20] = x[21] = x[22]
    x[8], x[9] = 0, 1
    cuts = (0.0, 0.2, 0.5, 0.9)
    merges = K.merge_tree(K.similarity_matrix(x, kind), method, 0.0)
    want = [K.cut_tree(150, merges, c).tolist() for c in cuts]
    seen, whole = [], K.merge_tree
    monkeypatch.setattr(K, "merge_tree", lambda s, *a: seen.append(len(s)) or whole(s, *a))
    for cells in (200, 4000):  # with the smaller one a single cluster is more than a block
        monkeypatch.setattr(K, "BLOCK_CELLS", cells)
        for most in (1, 12, 70):
            assert [v.tolist() for v in K.labels_by_rows(x, kind, method, cuts, 4, "single", most)] == want
            assert max(seen, default=0) <= most
            seen.clear()


@pytest.mark.parametrize("method", ["single", "density"])
def test_listed_and_searched_pairs_agree(method, monkeypatch):
    rng = np.random.default_rng(6)
    x = rng.normal(size=(15, 6))[rng.integers(0, 15, 120)] + rng.normal(size=(120, 6)) * 0.4
    s = K.similarity_matrix(x, "cosine")
    cuts = (0.3, 0.6, 0.9)
    tree = K.merge_tree(s, "single", 0.3)
    want = [(K.cut_tree(120, tree, c) if method == "single" else K.density_labels(s, c, 4)).tolist() for c in cuts]
    monkeypatch.setattr(K, "BLOCK_CELLS", 500)
    for most in (0, 700, 10**6):
        monkeypatch.setattr(K, "MOST_EDGES", most)
        assert [v.tolist() for v in K.labels_by_rows(x, "cosine", method, cuts, 4, "single")] == want


def test_density_and_constant_vectors():
    x = np.array([[1, 2, 3.0], [1, 2, 3.1], [3, 2, 1], [5, 5, 5]])
    s = K.similarity_matrix(x)
    assert s[3, 0] == 0 and s[3, 3] == 1
    assert K.density_labels(s, 0.9, 2).tolist() == [0, 0, 2, 3]
    assert K.density_labels(s, 0.9, 2, "group").tolist() == [0, 0, 2, 2]


def test_strong_plant_is_found(spark, sf):
    v = A.vectors(spark, sf, 1.5)
    found = K.cluster_devices(v.drop("label"), [0.4], "average", "cosine")
    from linefault.operators.measures import cluster_agreement

    assert cluster_agreement(found.join(v.select("device", "label"), "device"), "cluster_id", "label").first().ari > 0.99


@pytest.mark.parametrize("kind", K.SIMILARITIES)
def test_pairs_equal_matrix(spark, sf, kind):
    v = A.vectors(spark, sf, 0.7, 100)
    rows = {r.device: r for r in v.collect()}
    for r in K.pair_similarity(v, kind).limit(60).collect():
        assert r.similarity == pytest.approx(K.similarity_matrix(np.array([rows[r.a].vector, rows[r.b].vector]), kind)[0, 1])


def test_vectors_by_period(spark):
    day = dt.datetime(2024, 1, 1)
    rows = [(1, 9, i, day + dt.timedelta(hours=12 * i + 1), float(i)) for i in range(8)]
    tel = spark.createDataFrame(rows, "device long, node int, rec_id long, ts timestamp_ntz, tx double")
    periods = spark.createDataFrame([(1, 9, 1), (1, 9, 3)], "device long, node int, slot int")
    v = {r.slot: r.vector for r in K.device_vectors(tel, "tx", "2024-01-01", "2024-01-05", 12, periods, 24, 48).collect()}
    assert v == {1: [0.0, 0.0, 1.0, 2.0], 3: [3.0, 4.0, 5.0, 6.0]}


def test_types_and_combination(spark):
    one = spark.createDataFrame([(1, "maintenance"), (2, "service")], "device long, fault_type string")
    two = spark.createDataFrame([(1, "service"), (3, "service")], "device long, fault_type string")
    got = {r.device: r.fault_type for r in K.combine_types(one, two).collect()}
    assert got == {1: "maintenance", 2: "service", 3: "service"}
    assert {r.device: r.fault_type for r in K.combine_types(one, two, "all").collect()}[1] == "service"
