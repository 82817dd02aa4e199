import hashlib

import numpy as np
import pytest

from linefault.llm import substring_dedup as D
from linefault.llm import suffix_array as S


@pytest.mark.parametrize("small", [1024, 0])
@pytest.mark.parametrize("symbols", [1, 2, 4, 200, 5000])
def test_suffix_array_is_sorted(symbols, small, monkeypatch):
    """By buckets and by batches of buckets, over random, repeated and stretched strings."""
    monkeypatch.setattr(S, "SMALL_ALPHABET", small)
    rng = np.random.default_rng(symbols)
    for n in [*range(1, 30), 200]:
        t = rng.integers(0, symbols, n)
        if n % 3 == 0:
            t = np.concatenate([t, t, t[: n // 2]])
        if n % 3 == 1:
            t = np.repeat(t, rng.integers(1, 5, n))
        assert S.suffix_array(t).tolist() == sorted(range(len(t)), key=lambda i: t[i:].tolist())


@pytest.mark.parametrize("small", [1024, 0])
def test_one_symbol_and_long_periods(small, monkeypatch):
    monkeypatch.setattr(S, "SMALL_ALPHABET", small)
    assert S.suffix_array(np.zeros(5000, np.int64)).tolist() == list(range(4999, -1, -1))
    t = np.frombuffer(b"abcabcabd" * 700, np.uint8)
    raw = t.tobytes()
    assert S.suffix_array(t).tolist() == sorted(range(len(t)), key=lambda i: raw[i:])


def test_every_level_is_induced(spark, sf, monkeypatch):
    """On real text the recursion goes down to names that are all different, and each level is placed by an induction."""
    text = "\n".join(r.text or "" for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").limit(400).collect())[:200_000].encode()
    levels, placed, own, large = [], [], S.suffix_array, S._induce_large
    monkeypatch.setattr(S, "suffix_array", lambda t: levels.append(len(t)) or own(t))
    monkeypatch.setattr(S, "_induce_large", lambda t, *a: placed.append(len(t)) or large(t, *a))
    order = S.suffix_array(np.frombuffer(text, np.uint8))
    assert len(levels) > 2 and all(b <= a / 2 for a, b in zip(levels, levels[1:], strict=False))
    assert placed and set(placed) <= set(levels)
    some = order[:: max(1, len(order) // 2000)]
    assert all(text[a:] < text[b:] for a, b in zip(some, some[1:], strict=False))


def test_common_prefixes():
    text = b"abracadabra" * 3
    order = S.suffix_array(np.frombuffer(text, np.uint8))
    got = S.permuted_common_prefixes(text, order, 20)
    for a, b in zip(order[1:], order[:-1], strict=True):
        k = 0
        while k < 20 and max(a, b) + k < len(text) and text[a + k] == text[b + k]:
            k += 1
        assert got[a] == k


def test_wings_do_not_depend_on_cuts(monkeypatch):
    text = np.random.default_rng(1).integers(97, 101, 5000, dtype=np.uint8).tobytes()
    whole = D.segments(text)
    monkeypatch.setattr(D, "_PLACE_BITS", 10)
    monkeypatch.setattr(D, "_PLACE", np.uint64(2**10 - 1))
    parts = D.segments(text)
    assert set(parts[0]) & set(whole[0]) and parts[2][-1] == whole[2][-1] == len(text) - D.LENGTH


def brute(rows):
    first = {}
    texts = [(i, (t or "").encode()) for i, t, *_ in rows]
    for i, t in texts:
        for p in range(len(t) - 49 if i is not None else 0):
            k = t[p : p + 50]
            first[k] = min(first.get(k, i), i)
    out = []
    for i, t in texts:
        gone = np.zeros(len(t), bool)
        for p in range(len(t) - 49 if i is not None else 0):
            if first[t[p : p + 50]] < i:
                gone[p : p + 50] = True
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out.append((str(i), len(t), int(gone.sum()), runs, hashlib.sha256(np.frombuffer(t, np.uint8)[~gone].tobytes()).hexdigest()))
    return sorted(out)


def got(df):
    return sorted((str(r.doc_id), r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in D.remove_repeats(df).collect())


def test_against_brute_force(docs_of, odd):
    base = np.random.default_rng(0).integers(97, 123, 3000, dtype=np.uint8).tobytes().decode()
    rows = [(11, base[:400], "a"), (12, base[100:160] + "x" + base[300:349], "a"), (13, "a" * 500, "a"), (14, "b" + "a" * 120, "a"), (None, base[:200], "a"), (17, base[350:700], "a"), (17, base[:700], "a"), (18, base[349:399], "a"), (19, base[349:398], "a"), (20, "ab" * 100 + "é" * 60, "a"), (21, "ab" * 40 + "c" + "é" * 40, "a"), (0, base[1000:1100], "a"), (22, base, "a"), (22, base, "a"), *odd]
    assert got(docs_of(rows)) == brute(rows)


def test_whole_table(spark, sf):
    df = spark.read.parquet(f"{sf}/documents.parquet")
    assert got(df) == brute([(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()])


def test_empty(docs_of):
    assert D.remove_repeats(docs_of([])).count() == 0
