import itertools
import struct
import zlib

import numpy as np
import pytest
from tokenizers import Tokenizer

from linefault.llm import packing as P


@pytest.fixture(scope="module")
def encoder():
    return P.Encoder(P.tokenizer_path())


def plain(encoder, text):
    return Tokenizer.from_file(P.tokenizer_path()).encode(text, add_special_tokens=False).ids


def test_cached_ids_equal_the_tokenizers(encoder):
    texts = ["", "a b\x1cc", "<|endoftext|> x<|startoftext|>y", "don't I'LL é́  x y　z", "ΑΣ ΑΣ. İ ß ẞ", "à ̀b", "1234 5.6", "x" * 3000, "Über, ÀÉ!! ſs ab| | |a"]
    texts += ["".join(p) for p in itertools.product("aÀ.'9-", repeat=3)] + [chr(c).join("ab") + "." for c in range(0x250)]
    whole = Tokenizer.from_file(P.tokenizer_path())
    for text, coded in zip(texts, encoder(texts), strict=True):
        assert list(struct.unpack(f"<{len(coded) // 4}I", coded)) == whole.encode(text, add_special_tokens=False).ids, text


def test_combinations_fill_the_window():
    rows = P.combinations(64)
    assert (rows.sum(axis=1) == 64).all() and len(np.unique(rows, axis=0)) == len(rows)


def test_least_squares_reaches_a_known_mix():
    rows = P.combinations(32)
    true = np.zeros(len(rows))
    true[::7] = 10
    histogram = np.bincount(rows.ravel(), np.repeat(true, 3), 33)
    histogram[0] = 0
    x = P.solve_counts(rows, histogram, 200)
    left = np.bincount(rows.ravel(), np.repeat(x, 3), 33)[1:] - histogram[1:]
    assert np.abs(left * np.arange(1, 33)).sum() < 0.02 * (histogram * np.arange(33)).sum() and (x >= 0).all()


def test_plan_uses_each_piece_once():
    histogram = np.random.default_rng(0).integers(0, 50, 257)
    histogram[0] = 0
    used = np.zeros(257, int)
    tokens = sequences = 0
    for lengths, times in P.plan(histogram, 256):
        assert sum(lengths) <= 256
        sequences += times
        tokens += times * sum(lengths)
        for x in lengths:
            used[x] += times
    assert (used == histogram).all() and tokens / (256 * sequences) > 0.97


def check(df, rows):
    got = P.pack(df).toPandas()
    want = {}
    for i, t in rows:
        want.setdefault(i, []).append(np.array([*plain(None, t or ""), 1], "<u4"))
    for i, part in got.groupby("doc_id", dropna=False):
        ids = want[None if i != i else int(i)]
        assert part["length"].sum() == sum(map(len, ids))
        for r in part.itertuples():
            assert any(len(x) == r.doc_tokens and zlib.crc32(x[r.start : r.start + r.length].tobytes()) == r.ids_crc32 for x in ids)
    for _, part in got.groupby("sequence_id"):
        part = part.sort_values("offset")
        assert part["offset"].tolist() == [0, *np.cumsum(part["length"])[:-1]] and part["length"].sum() <= P.WINDOW
    return got


def test_odd_rows(docs_of, odd):
    assert len(check(docs_of(odd), [(i, t) for i, t, _ in odd])) >= len(odd)


def test_whole_table(spark, sf):
    df = spark.read.parquet(f"{sf}/documents.parquet")
    got = check(df, [(r.doc_id, r.text) for r in df.collect()])
    assert got["length"].sum() / got["sequence_id"].nunique() / P.WINDOW > 0.97


def test_empty(docs_of):
    assert P.pack(docs_of([])).count() == 0
