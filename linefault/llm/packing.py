"""Packing documents into fixed windows by non-negative least squares over length combinations.

Each document is tokenised once and cut at multiples of the window, so all but its last piece fill
a sequence of their own. The last pieces go by their length histogram, which has at most `window` bins and
is all that reaches the driver: combinations of up to DEPTH lengths that fill the window exactly are
enumerated, repeat counts are solved by non-negative least squares against the histogram, rounded
down to what the histogram holds, and the residual is packed greedily, best fit first. The plan is a list of
patterns with repeat counts; pieces meet it by their rank within their length, so neither plan
nor driver grows with the input.

Defined cases: a null or empty text is one piece of the end mark alone; repeated rows are packed each
for itself (pieces then carry equal doc_id); an empty table gives an empty result.
"""

from __future__ import annotations

import os
import struct
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import small_batches, staged, table

WINDOW = 2048
END_ID = 1
DEPTH = 3
TOKENIZER = "word_bpe_49k.json"
#: Third lengths tried beside each pair in a combination of three; a rule, so the columns stay some thousands.
THIRDS = 24
SWEEPS = 60
#: Words that a worker remembers before it starts anew.
CACHE = 600_000
#: Texts encoded at once.
BATCH = 256
ROWS_PER_SLICE = 1_000_000


class Encoder:
    """Token ids (as little-endian bytes) of whole texts, word by word from a bounded cache.

    The tokenizer drops white space and never joins across it, so the ids of a text are those of its
    space-separated parts in order. A part that is plain letters and then plain punctuation goes to the merge model
    directly, as the tokenizer's own rules would cut it; every other part goes through the whole
    tokenizer, and so do texts with control characters that split() and the tokenizer see differently.
    """

    ODD = "\x1c\x1d\x1e\x1f"
    MARKS = ".,!?;:|#$%&*"
    #: Below this code point lower-casing and composition go letter by letter.
    PLAIN = "\u0180"

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.cache: dict[str, bytes] = {}
        self.pieces: dict[str, bytes] = {"": b""}
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves
        hidden = [b for b in range(256) if b not in set(shown)]
        self.letters = [chr(b) if b in set(shown) else chr(256 + hidden.index(b)) for b in range(256)]

    def _packed(self, ids: list[int]) -> bytes:
        return struct.pack(f"<{len(ids)}I", *ids)

    def _whole(self, text: str) -> bytes:
        return self._packed(self.tokenizer.encode(text, add_special_tokens=False).ids)

    def _piece(self, piece: str) -> bytes:
        found = self.pieces.get(piece)
        if found is None:
            shown = piece if piece.isascii() else "".join(self.letters[b] for b in piece.encode())
            found = self.pieces[piece] = self._packed([t.id for t in self.tokenizer.model.tokenize(shown)])
        return found

    def _word(self, word: str) -> bytes:
        letters = word.rstrip(self.MARKS)
        small = letters.lower()
        if len(small) <= 64 and (small.isalpha() or not small) and max(word) < self.PLAIN and len(small) == len(letters):
            return self._piece(small) + self._piece(word[len(letters) :])
        return self._whole(word)

    def __call__(self, texts: list[str]) -> list[bytes]:
        odd = [any(c in text for c in self.ODD) for text in texts]
        words = [[] if o else text.split() for o, text in zip(odd, texts, strict=True)]
        new = set().union(*words).difference(self.cache)
        if len(self.cache) + len(new) > CACHE:
            self.cache, self.pieces, new = {}, {"": b""}, set().union(*words)
        for word in new:
            self.cache[word] = self._word(word)
        find = self.cache.__getitem__
        return [self._whole(text) if o else b"".join(map(find, found)) for o, text, found in zip(odd, texts, words, strict=True)]


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """One encoder a worker process, so its cache serves all tasks of the worker."""
    if path not in _ENCODERS:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def document_pieces(docs: DataFrame, window: int = WINDOW, tokenizer: str = TOKENIZER) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens): each document cut at multiples of the window."""

    def run(batches):
        encode, end = encoder(tokenizer_path(tokenizer)), struct.pack("<I", END_ID)
        for whole in batches:
            for at in range(0, max(1, whole.num_rows), BATCH):
                batch = whole.slice(at, BATCH)
                rows: list[tuple] = []
                texts = [x or "" for x in batch["text"].to_pylist()]
                for i, coded in zip(batch["doc_id"].to_pylist(), encode(texts), strict=True):
                    ids = coded + end
                    n = len(ids) // 4
                    rows += [(i, s, min(window, n - s), zlib.crc32(ids[4 * s : 4 * (s + window)]), n) for s in range(0, n, window)]
                cols = list(zip(*rows, strict=True)) or [[]] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long")


def combinations(window: int, depth: int = DEPTH, thirds: int = THIRDS) -> np.ndarray:
    """Rows of `depth` lengths (0 for none), not rising, that fill the window: all pairs, and of each
    pair that leaves room the third lengths on an even grid."""
    found = {(window, 0, 0)} | {(max(a, window - a), min(a, window - a), 0) for a in range(1, window)} if depth >= 2 else {(window, 0, 0)}
    if depth >= 3:
        step = max(1, window // (3 * thirds))
        for a in range(1, window // 3 + 1):
            grid = range(a, (window - a) // 2 + 1, step) if a % step else range(a, (window - a) // 2 + 1)
            found |= {tuple(sorted((a, b, window - a - b), reverse=True)) for b in grid}
    return np.array(sorted(found, reverse=True), np.int64)


def solve_counts(rows: np.ndarray, histogram: np.ndarray, sweeps: int = SWEEPS) -> np.ndarray:
    """Non-negative least squares of A x = histogram, column j of A counting the lengths of rows[j].

    Projected gradient with momentum; A has at most DEPTH entries a column and is never built. Residuals are weighed by
    length, so tokens left over count and not pieces.
    """
    weight = np.arange(len(histogram), dtype=np.float64) / len(histogram)
    weight[0] = 0.0
    target = histogram * weight
    apply = lambda x: np.bincount(rows.ravel(), np.repeat(x, rows.shape[1]), len(histogram)) * weight
    back = lambda r: (r * weight)[rows].sum(axis=1)
    probe = np.ones(len(rows))
    for _ in range(20):  # the largest eigenvalue gives the step
        probe = back(apply(probe))
        top = np.linalg.norm(probe)
        probe /= max(top, 1e-300)
    x = y = np.zeros(len(rows))
    t = 1.0
    for _ in range(sweeps * 10):
        z = np.maximum(0.0, y - back(apply(y) - target) / max(top, 1e-300))
        s = (1 + np.sqrt(1 + 4 * t * t)) / 2
        x, y, t = z, z + (t - 1) / s * (z - x), s
    return x


def plan(histogram: np.ndarray, window: int = WINDOW, depth: int = DEPTH) -> list[tuple[tuple[int, ...], int]]:
    """Patterns (lengths, repeats) that use each piece of the histogram exactly once."""
    left = histogram.astype(np.int64).copy()
    patterns: list[tuple[tuple[int, ...], int]] = []

    def take(lengths: tuple[int, ...], most: int) -> None:
        need: dict[int, int] = {}
        for x in lengths:
            need[x] = need.get(x, 0) + 1
        times = int(min([most, *(left[x] // k for x, k in need.items())]))
        if times > 0:
            for x, k in need.items():
                left[x] -= k * times
            patterns.append((lengths, times))

    rows = combinations(window, depth)
    rows = rows[np.where(rows > 0, left[rows] > 0, True).all(axis=1)]
    if len(rows):
        x = solve_counts(rows, left.astype(np.float64))
        for j in np.argsort(-x, kind="stable"):
            if x[j] < 1:
                break
            take(tuple(int(v) for v in rows[j] if v), int(x[j]))
    while left.any():  # the longest piece left, and always the longest that still fits
        lengths, room = [], window
        held = left.copy()
        while room > 0:
            fit = np.flatnonzero(held[: room + 1])
            if not len(fit):
                break
            lengths.append(int(fit[-1]))
            held[fit[-1]] -= 1
            room -= int(fit[-1])
        take(tuple(lengths), int(left.max()))
    return patterns


def plan_slots(patterns: list[tuple[tuple[int, ...], int]], window: int) -> pd.DataFrame:
    """(length, first, last, base, offset): ranks first..last of a length take sequences base.. at offset."""
    used: dict[int, int] = {}
    rows, base = [], 0
    for lengths, times in patterns:
        offset = 0
        for x in lengths:
            rows.append((x, used.get(x, 0), used.get(x, 0) + times - 1, base, offset))
            used[x] = used.get(x, 0) + times
            offset += x
        base += times
    return pd.DataFrame(rows, columns=["length", "first", "last", "base", "offset"])


def pack(docs: DataFrame, window: int = WINDOW, tokenizer: str = TOKENIZER, depth: int = DEPTH) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    spark = docs.sparkSession
    small_batches(spark)
    pieces = staged(document_pieces(docs, window, tokenizer).withColumn("piece_no", F.monotonically_increasing_id()), "pieces")
    histogram = np.zeros(window + 1, np.int64)
    for row in pieces.groupBy("length").count().collect():  # at most `window` rows
        histogram[row["length"]] = row["count"]
    slots = plan_slots(plan(histogram, window, depth), window)
    slices = max(16, -(-int(histogram.sum()) // ROWS_PER_SLICE))
    cut = pieces.withColumn("slice", F.pmod(F.xxhash64("piece_no"), F.lit(slices)).cast("int"))
    # Rank within a length in two steps, so that a length with a third of all pieces is spread.
    before = Window.partitionBy("length").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = cut.groupBy("length", "slice").count().select("length", "slice", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("ahead"))
    inner = Window.partitionBy("length", "slice").orderBy("doc_id", "start", "piece_no")
    ranked = cut.withColumn("place", F.row_number().over(inner)).join(starts, ["length", "slice"]).withColumn("rank", F.col("ahead") + F.col("place") - 1)
    if not len(slots):
        return ranked.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", F.col("rank").alias("sequence_id"), F.col("start").alias("offset"))

    table_of = spark.sparkContext.broadcast({int(k): part[["first", "base", "offset"]].to_numpy(np.int64) for k, part in slots.groupby("length")})

    @F.pandas_udf("struct<sequence_id:long,offset:long>")
    def placed(length: pd.Series, rank: pd.Series) -> pd.DataFrame:
        sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
        lengths, ranks = length.to_numpy(), rank.to_numpy()
        for x in np.unique(lengths):
            at = np.flatnonzero(lengths == x)
            slot = table_of.value[int(x)]
            j = np.searchsorted(slot[:, 0], ranks[at], side="right") - 1
            sequence[at] = slot[j, 1] + ranks[at] - slot[j, 0]
            offset[at] = slot[j, 2]
        return pd.DataFrame({"sequence_id": sequence, "offset": offset})

    return ranked.withColumn("at", placed("length", "rank")).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "at.sequence_id", "at.offset")


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
