"""Exact dedup, near dedup, lines, mixing, URLs and quality against plain Python, and on odd rows."""

import collections
import hashlib
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from linefault.llm import exact_dedup as E
from linefault.llm import line_dedup as LD
from linefault.llm import mixing as MX
from linefault.llm import ngram_join as G
from linefault.llm import quality as Q
from linefault.llm import url_filter as U
from linefault.llm.graph import connected_components


def documents(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


# Exact


def lowered(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


@pytest.mark.parametrize("bits", [2**12, 2**27])
def test_exact_against_groups(spark, sf, bits):
    df = documents(spark, sf)
    groups = collections.defaultdict(list)
    for r in df.collect():
        groups[lowered(r.text)].append(r.doc_id)
    want = {i: (max(g), len(g), i == max(g), hashlib.sha256(t.encode()).hexdigest()) for t, g in groups.items() for i in g}
    assert {r.doc_id: (r.keep_id, r.group_size, r.kept, r.text_sha256) for r in E.exact_dedup_report(df, max_bits=bits).collect()} == want
    assert {r.doc_id for r in E.exact_dedup(df, max_bits=bits).collect()} == {i for i, w in want.items() if w[2]}


def test_exact_odd(docs_of, odd):
    df = docs_of([*odd, (7, "É A", "a"), (8, "É a", "a"), (9, "é a", "a")])
    out = E.exact_dedup(df)
    assert out.columns == df.columns
    assert sorted(str(r.doc_id) for r in out.collect()) == sorted(map(str, [2, None, 3, 4, 5, 6, 8, 9]))
    report = E.exact_dedup_report(df).collect()
    assert len(report) == 11 and sum(r.kept for r in report) == 8
    assert E.exact_dedup(docs_of([])).count() == 0 == E.exact_dedup_report(docs_of([])).count()


def test_clashing_columns_keep_their_values(spark, docs_of, odd):
    """Every operator that returns rows gives the extra columns back as they were."""
    df = docs_of([(i, t, s) for i, t, s in odd if i != 3])
    extra = lambda x: {(r["doc_id"], r["text"]): (r["digest"], r["size.x"], r["lang"]) for r in x.collect()}
    want = extra(df)
    for out in (E.exact_dedup(df), G.drop_near_duplicates(df), MX.mix_sources(df), Q.keep_quality(df, spark.createDataFrame([], "doc_id long, quality long"))):
        assert out.columns == df.columns and all(want[k] == v for k, v in extra(out).items())


def test_exact_has_no_python(docs_of, odd):
    plan = E.exact_dedup_report(docs_of(odd))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Pandas" not in plan and "Arrow" not in plan


# Near


def test_bands_reach_the_recall():
    for recall in (0.9, 0.99, 0.9999):
        bands, rows = G.choose_bands(0.8, recall)
        assert 1 - (1 - 0.8**rows) ** bands >= recall and bands * rows <= G.MOST_HASHES
    with pytest.raises(ValueError):
        G.choose_bands(0.1, 0.999999, 4)


def test_recall_near_the_limit():
    """Pairs planted between 0.8 and 0.85: how many meet in a band and pass the sketch. Both together keep the target recall."""
    rng = np.random.default_rng(4)
    bands, rows = G.choose_bands()
    hasher = G.Hasher(G.N, bands, rows)
    met = passed = total = 0
    while total < 2500:
        words = [f"w{x}" for x in rng.integers(0, 10**6, int(rng.integers(40, 700)))]
        other = list(words)
        for at in rng.choice(len(words), max(1, len(words) // 45), replace=False):
            other[at] = "changed"
        a, b = (hasher.ngrams(" ".join(x).encode()) for x in (words, other))
        both = len(np.intersect1d(a, b))
        if not 0.8 <= both / (len(a) + len(b) - both) <= 0.85:
            continue
        total += 1
        (h, s), (k, t) = hasher.band_hashes(a), hasher.band_hashes(b)
        met += (h == k).any()
        passed += G.may_reach(*[np.frombuffer(x, "<u2")[None, :] for x in (s, t)], np.array([len(a) + len(b)]), 0.8)[0]
    assert met / total >= 0.999 and passed == total


def near_brute(rows):
    sets, parent = [G.ngram_set((t or "").encode()) for _, t in rows], list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if (rows[i][1] or "") == (rows[j][1] or "") or G.jaccard(sets[i], sets[j]) >= 0.8:
                parent[find(i)] = find(j)
    return [find(i) for i in range(len(rows))]


def same_partition(a, b):
    return len(set(zip(a, b, strict=True))) == len(set(a)) == len(set(b))


def test_near_against_all_pairs(spark):
    rng = np.random.default_rng(0)
    words = [f"w{i}" for i in range(300)]
    rows = []
    for g in range(12):
        base = rng.choice(words, 80).tolist()
        for _ in range(9):
            copy = list(base)
            for at in rng.choice(80, rng.integers(0, 8), replace=False):
                copy[at] = str(rng.choice(words))
            rows.append((len(rows), " ".join(copy)))
    rows += [(len(rows) + i, t) for i, t in enumerate(["", None, " ", "one two", "one  two", "one two three", "a b c d e f g", "a b c d e f g"])]
    got = {r.doc_id: r for r in G.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert same_partition([got[i].class_id for i, _ in rows], near_brute(rows))
    sizes = collections.Counter(r.class_id for r in got.values())
    assert all(r.class_size == sizes[r.class_id] for r in got.values())
    assert sum(r.keep for r in got.values()) == len(sizes)


def test_tiles_find_the_same(spark, monkeypatch):
    rng = np.random.default_rng(1)
    base = rng.choice([f"v{i}" for i in range(500)], 60).tolist()
    rows = []
    for i in range(60):
        copy = list(base)
        for at in rng.choice(60, rng.integers(1, 6), replace=False):
            copy[at] = f"n{rng.integers(0, 40)}"
        rows.append((i, " ".join(copy)))
    monkeypatch.setattr(G, "TILE", 4)
    got = {r.doc_id: r.class_id for r in G.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert same_partition([got[i] for i, _ in rows], near_brute(rows))


@pytest.mark.parametrize("tile", [1024, 7])
def test_links_against_all_pairs(spark, monkeypatch, tile):
    monkeypatch.setattr(G, "LINK_TILE", tile)
    rng = np.random.default_rng(2)
    words = [f"w{i}" for i in range(400)]
    texts = ["a b c d e f g", "a  b c d e f g", "a\tb c d e f g", "", None]
    for copies in (3, 90):
        base = rng.choice(words, 90).tolist()
        for _ in range(copies):
            copy = list(base)
            for at in rng.choice(90, rng.integers(0, 4), replace=False):
                copy[at] = str(rng.choice(words))
            texts.append(" ".join(copy))
    rows = list(enumerate(texts + texts[:2] + texts[-3:]))
    sets = [G.ngram_set((t or "").encode()) for _, t in rows]
    want = {i: sum(j != i and ((t or "") == (u or "") or G.jaccard(sets[i], sets[j]) >= 0.8) for j, u in rows) for i, t in rows}
    got = {r.doc_id: r.n_links for r in G.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == want


def test_near_odd(docs_of, odd):
    df = docs_of(odd)
    assert G.near_duplicates(df).count() == len(odd)
    out = G.drop_near_duplicates(df)
    assert out.columns == df.columns and out.count() == 6
    assert G.near_duplicates(docs_of([])).count() == 0 == G.drop_near_duplicates(docs_of([])).count()


def test_components(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 50), (51, 100), (200, 200)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(41), 0), **dict.fromkeys((50, 51, 100), 50)}


# Lines


def lines_brute(rows):
    holders = collections.defaultdict(set)
    for i, t in rows:
        for line in (t or "").encode().split(b"\n"):
            k = LD.line_key(line)
            if k is not None and i is not None:
                holders[k].add(i)
    out = []
    for i, t in rows:
        lines = (t or "").encode().split(b"\n")
        kept = [x for x in lines if i is None or (k := LD.line_key(x)) is None or len(holders[k]) < 2 or min(holders[k]) == i]
        out.append((str(i), len(lines), len(lines) - len(kept), hashlib.sha256(b"\n".join(kept)).hexdigest()))
    return sorted(out)


def applied(index, df):
    return sorted((str(r.doc_id), r.n_lines, r.n_dropped, r.kept_sha256) for r in index.apply(df).collect())


LINES = [(1, "A shared line here\nshort\nalone in this one"), (2, "  a SHARED line here \t\nmine mine mine\nmine mine mine"), (3, "a shared line here\nmine mine mine"), (4, "éééééééééé\nshort"), (5, "éééééééééé\nÉéééééééééé")]


def test_lines(docs_of, odd):
    rows = [(i, t) for i, t, _ in odd] + [(10 + i, t) for i, t in LINES]
    df = docs_of([(i, t, "a") for i, t in rows])
    assert applied(LD.LineIndex.build(df), df) == lines_brute(rows)
    assert applied(LD.LineIndex.build(docs_of([])), docs_of([])) == []


def test_insertions_and_deletions_equal_a_fresh_build(spark, docs_of):
    frame = lambda rows: docs_of([(i, t, "a") for i, t in rows])
    index = LD.LineIndex.build(frame(LINES[:2])).insert(frame(LINES[2:]))
    assert applied(index, frame(LINES)) == lines_brute(LINES)
    left = [r for r in LINES if r[0] not in (1, 4)]
    less = index.delete(spark.createDataFrame([(1,), (4,)], "doc_id long"))
    assert applied(less, frame(left)) == lines_brute(left)
    fresh = LD.LineIndex.build(frame(left))
    key = lambda ix: sorted((r.hi, r.lo, r.first_doc, r.last_doc, r.n_refs) for r in ix.counts.collect())
    assert key(less) == key(fresh)
    assert applied(less.insert(frame([LINES[0], LINES[3]])), frame(LINES)) == lines_brute(LINES)


@pytest.mark.parametrize("most", [2**20, 2])
def test_filters_that_are_not_broadcast(spark, sf, docs_of, odd, monkeypatch, most):
    """Beyond the broadcast limit the keys go to the shards, in as many parts as it takes, with the same result."""
    monkeypatch.setattr(LD, "MAX_FILTER_BYTES", 0)
    monkeypatch.setattr(LD, "KEYS_PER_GROUP", most)
    monkeypatch.setattr(LD, "KEYS_PER_SHARD", 1)
    rows = [(i, t) for i, t, _ in odd] + [(10 + i, t) for i, t in LINES]
    df = docs_of([(i, t, "a") for i, t in rows])
    index = LD.LineIndex.build(df)
    assert index.probe() is None and index.shards > 1
    assert applied(index, df) == lines_brute(rows)
    asked = LD.references(df)
    kept = index.sharded_hits(asked, 5)
    missed = asked.join(kept, ["doc_id", "hi", "lo"], "left_anti").join(index.counts.where("first_doc < last_doc"), ["hi", "lo"], "left_semi")
    assert missed.count() == 0 and kept.count() < asked.count()


def test_cuckoo_shard():
    keys = np.random.default_rng(0).integers(-(2**62), 2**62, 900)
    shard = LD.CuckooShard(256)
    shard.insert(keys)
    probe = LD.ShardedProbe({0: shard.to_bytes()}, 1, 256)
    assert probe.hits(np.zeros(900, np.int64), keys).all()
    other = np.random.default_rng(1).integers(-(2**62), 2**62, 20_000)
    assert probe.hits(np.zeros(20_000, np.int64), other).mean() < 0.01
    again = LD.CuckooShard.from_bytes(shard.to_bytes())
    again.delete(keys)
    assert not again.cells.any() and not again.stash


# Mixing


def test_targets_and_mix(spark, docs_of):
    rows = [(i, "w " * (1 + i % 7), ["a", "b", "c", None][min(3, i // 100)]) for i in range(330)]
    df = docs_of(rows)
    out = MX.mix_report(df).collect()
    by = {}
    for r, (_, _, s) in zip(sorted(out, key=lambda r: r.doc_id), rows, strict=True):
        by.setdefault(s, []).append(r)
    total = sum(r.size for r in out)
    assert sum(v[0].target for v in by.values()) == pytest.approx(total)
    for v in by.values():
        assert v[0].target <= 3 * v[0].source_size + 1e-9
        assert abs(sum(r.taken for r in v) - v[0].target) <= 2 * 7
        assert all(r.taken <= 3 * r.size for r in v)
    assert sorted(out) == sorted(MX.mix_report(df).collect())
    mixed = MX.mix_sources(df)
    assert mixed.columns == df.columns
    assert {k: v for k, v in collections.Counter(r.doc_id for r in mixed.collect()).items()} == {r.doc_id: r.taken // r.size for r in out if r.taken}


def test_mixing_odd(docs_of, odd):
    assert MX.mix_report(docs_of(odd)).count() == len(odd)
    assert MX.mix_report(docs_of([])).count() == 0 == MX.mix_sources(docs_of([])).count()
    assert MX.mix_report(docs_of([(1, None, None), (2, "", "a")])).agg(F.sum("taken")).first()[0] == 0
    report, mixed = MX.mix_report(docs_of(odd)), MX.mix_sources(docs_of(odd))
    words = lambda t: MX.word_count(F.col(t))
    assert mixed.agg(F.sum(words("text"))).first()[0] == report.agg(F.sum("taken")).first()[0]


def test_mix_holds_what_it_reports(docs_of):
    """Rows of one id: the mix takes exactly the words that the report names, and no row more than thrice."""
    rows = [(i % 30, "w " * (3 + i % 4), "abc"[i % 3]) for i in range(90)] + [(5, "same same", "a")] * 7
    df = docs_of(rows)
    mixed = MX.mix_sources(df).collect()
    assert sum(len(r.text.split()) for r in mixed) == MX.mix_report(df).agg(F.sum("taken")).first()[0]
    have, took = collections.Counter((r[0], r[1], r[2]) for r in rows), collections.Counter((r.doc_id, r.text, r.source) for r in mixed)
    assert all(n <= 3 * have[k] for k, n in took.items())


@pytest.mark.parametrize("slices", [64, 4096])
def test_slices_change_nothing(docs_of, slices):
    df = docs_of([(i, "w " * (1 + i % 3), "ab"[i % 2]) for i in range(200)])
    sized, _ = MX._sized(df, "doc_id", "text", "source")
    targets = MX.source_targets(sized)
    draw = lambda n: sorted((r.doc_id, r.copies) for r in MX.systematic_copies(sized, targets, slices=n).collect())
    assert draw(slices) == draw(1)


def test_mixing_has_no_python(docs_of, odd):
    for df in (MX.mix_report(docs_of(odd)), MX.mix_sources(docs_of(odd))):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "Python" not in plan and "Pandas" not in plan and "Arrow" not in plan


# URLs

URLS = [None, "", "no scheme/x", "http://", "http://x.net", "http://x.net/", "HTTP://WWW.Example.NET/en/1?q#f", "http://example.net/EN/", "http://a.example.com/de/x", "http://example.com/de", "http://notexample.com/de/", "http://q.org/fr/?a", "http://q.org/fr#x/fr/", "http://net/", "http://spam-farm.example.org/a", "http://www.spam-farm.example.org", "http://spam-farm.example.org/fr/1", "a://b://c.net/x", "http://x.net?/", "http://x.net:80/", "http://casino-win.example.com", "https://me:pw@www.casino-win.example.com:443?x=1", "http://free-bets.example.com./", "http://me@example.net/en/", "http://" + "a." * 3000 + "net/"]


def judge(url):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    host = rest
    for c in "/?#":
        host = host.split(c, 1)[0]
    path = rest[len(host) :]
    for c in "?#":
        path = path.split(c, 1)[0]
    host = lowered(host)
    fits = lambda h, p: (host == h or host.endswith("." + h)) and path.startswith(p)
    rules = [(len(h + p), h + p, v) for h, p, v in U.RULES if fits(h, p)]
    if rules:
        return host, path, *max(rules)[1:]
    bare = re.sub(r"\.+$", "", re.sub(r":[0-9]*$", "", host.rsplit("@", 1)[-1]))
    listed = any(bare == x[:-1] or bare.endswith("." + x[:-1]) for x in U.LISTED) and (path or "/").startswith("/")
    return host, path, None, "block" if listed else "allow"


def test_urls(spark):
    df = spark.createDataFrame([(i, u, "clash") for i, u in enumerate(URLS)], "page_id long, url string, url_keys string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in U.filter_urls(df, *U.default_lists(spark)).collect()}
    assert got == {i: judge(u) for i, u in enumerate(URLS)}
    assert U.filter_urls(df.where("false"), *U.default_lists(spark)).count() == 0
    rules, listed = U.default_lists(spark)
    assert {r.verdict for r in U.filter_urls(df, rules.where("false"), listed.where("false")).collect()} == {"allow"}


def test_url_lists_of_odd_entries(spark):
    """Null and repeated entries, a block list alone, rules alone, and many path lengths."""
    df = spark.createDataFrame(list(enumerate(URLS)), "page_id long, url string")
    rules, listed = U.default_lists(spark)
    judged = lambda r, x: {i.page_id: (i.rule, i.verdict) for i in U.filter_urls(df, r, x).collect()}
    more = rules.unionByName(rules).unionByName(spark.createDataFrame([(None, "/", "block"), ("net", None, "block"), (None, None, None)], rules.schema))
    assert judged(more, listed.unionByName(listed).unionByName(spark.createDataFrame([(None,)], listed.schema))) == judged(rules, listed)
    alone = judged(rules.where("false"), listed)
    assert all(r is None for r, _ in alone.values()) and {v for _, v in alone.values()} == {"allow", "block"}
    assert {v for r, v in judged(rules, listed.where("false")).values() if r is None} == {"allow"}
    long = rules.unionByName(spark.createDataFrame([("none.example", "/" + "x" * n, "block") for n in range(150)], rules.schema))
    assert judged(long, listed) == judged(rules, listed)


def test_url_false_positives_are_removed(spark, monkeypatch):
    monkeypatch.setattr(U, "may_contain", lambda blocks, hashes: np.ones(len(hashes), bool))
    df = spark.createDataFrame(list(enumerate(URLS)), "page_id long, url string")
    got = {r.page_id: r.verdict for r in U.filter_urls(df, *U.default_lists(spark)).collect()}
    assert got == {i: judge(u)[3] for i, u in enumerate(URLS)}


# Quality


def test_quality_on_held_out_labels(spark, sf):
    d = sf.replace("0.001", "0.01")
    scores = {r.doc_id: r for r in Q.quality_scores(documents(spark, d), spark.read.parquet(f"{d}/labels.parquet")).collect()}
    rows = [(scores[r.doc_id], r.quality) for r in spark.read.parquet(f"{d}/labels.parquet").collect() if zlib.crc32(str(r.doc_id).encode()) % 3 == 1]
    assert all(s.held_out for s, _ in rows)
    assert np.mean([s.predicted == q for s, q in rows]) > 0.95
    good, bad = [s.score for s, q in rows if q == 1], [s.score for s, q in rows if q == 0]
    assert np.mean([g > b for g in good for b in bad]) > 0.98


def test_quality_never_reads_held_out_labels(spark, sf):
    docs, labels = documents(spark, sf), spark.read.parquet(f"{sf}/labels.parquet")
    turned = labels.withColumn("quality", F.when(Q.held_out(), 1 - F.col("quality")).otherwise(F.col("quality")))
    key = lambda x: sorted((r.doc_id, round(r.score, 9)) for r in Q.quality_scores(docs, x).collect())
    assert key(labels) == key(turned)


def test_quality_equals_its_definition(spark, sf):
    """The discriminant again, from the statistics of all learned rows, by plain numpy and dense inverses."""
    docs, labels = documents(spark, sf), spark.read.parquet(f"{sf}/labels.parquet")
    texts = {r.doc_id: np.array(Q.statistics(r.text)) for r in docs.collect()}
    known = [(r.doc_id, r.quality) for r in labels.collect() if r.quality is not None and r.doc_id in texts and zlib.crc32(str(r.doc_id).encode()) % 3 != 1]
    parts = []
    for k in (0, 1):
        x = np.stack([texts[i] for i, q in known if q == k])
        cov = np.cov(x.T, bias=True)
        cov = (1 - Q.SHRINKAGE) * cov + Q.SHRINKAGE * np.diag(np.diag(cov)) + Q.RIDGE * np.eye(x.shape[1])
        parts.append((x.mean(axis=0), np.linalg.inv(cov), np.linalg.slogdet(cov)[1], np.log((len(x) + 1) / (len(known) + 2))))
    density = lambda v, m, inv, det, prior: prior - 0.5 * ((v - m) @ inv @ (v - m) + det)
    for r in Q.quality_scores(docs, labels).collect():
        away = np.clip(density(texts[r.doc_id], *parts[1]) - density(texts[r.doc_id], *parts[0]), -Q.CLIP, Q.CLIP)
        assert r.score == pytest.approx(1 / (1 + np.exp(-away)), rel=1e-4, abs=1e-9) and r.predicted == int(r.score >= 0.5)


def test_quality_odd(spark, docs_of, odd):
    none = spark.createDataFrame([], "doc_id long, quality long")
    rows = Q.quality_scores(docs_of(odd), none).collect()
    assert len(rows) == len(odd) and {r.score for r in rows} == {0.5}
    assert Q.quality_scores(docs_of([]), none).count() == 0
    assert Q.keep_quality(docs_of(odd), none).columns == docs_of(odd).columns
