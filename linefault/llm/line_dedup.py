"""Incremental line deduplication: sharded cuckoo filters over exact reference-count tables.

A line's key is the line without white space at its ends and with A-Z lower-cased. The reference
table holds one row per (key, document); the count table holds per key its first and last document and its number of
references. A key of at least MIN_CHARS code points that two documents hold is shared, and all
its lines go, except in the first document. Shared keys sit in cuckoo filters, one per shard of
the key space: a document whose lines all miss the filters passes straight through, and only possible hits
meet the exact table. Since cuckoo filters support deletion and the tables are exact, documents can be
inserted and removed, and the result is the one of a fresh build over what is left.

Defined cases: null or empty text is one empty line; rows with the same doc_id are one document for
sharing, and each gives its own result row; rows with a null doc_id hold no references and lose no lines;
an empty table gives an empty result; only id and text are read.
"""

from __future__ import annotations

import hashlib
import struct
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import join_by_weight, power_of_two, small_batches, staged, table

MIN_CHARS = 10
SPACE = b" \t\n\x0b\x0c\r"
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
SLOTS, KICKS = 4, 500
KEYS_PER_SHARD = 50_000
#: The filters are broadcast up to this size (about 25 million shared keys). Beyond it the keys go to the filters: 24 bytes
#: each, dealt by shard, and by document as well, so that a group holds about so many keys and a frequent line is spread.
MAX_FILTER_BYTES = 64 * 2**20
KEYS_PER_GROUP = 2**20


def line_key(line: bytes) -> bytes | None:
    """The key of a line, or None if it is shorter than MIN_CHARS code points."""
    key = line.strip(SPACE).translate(LOWER)
    if len(key) < MIN_CHARS or (not key.isascii() and len(key.decode("utf-8", "replace")) < MIN_CHARS):
        return None
    return key


def key_hash(key: bytes) -> tuple[int, int]:
    return struct.unpack("<qq", xxhash.xxh3_128_digest(key))


class CuckooShard:
    """A cuckoo filter of 16-bit fingerprints, four to a bucket, with a stash for what doesn't fit."""

    def __init__(self, buckets: int, cells: np.ndarray | None = None, stash: list[int] | None = None):
        self.buckets = buckets
        self.cells = np.zeros((buckets, SLOTS), np.uint16) if cells is None else cells
        self.stash = stash or []

    @staticmethod
    def places(lo: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Fingerprint (never 0) and both buckets of each key."""
        h = lo.astype(np.uint64)
        mark = (h & np.uint64(0xFFFF)).astype(np.uint16)
        mark[mark == 0] = 1
        one = ((h >> np.uint64(16)) & np.uint64(buckets - 1)).astype(np.int64)
        return mark, one, CuckooShard.other(one, mark, buckets)

    @staticmethod
    def other(bucket, mark, buckets: int):
        return bucket ^ ((np.asarray(mark, np.int64) * 0x5BD1E995) & (buckets - 1))

    def insert(self, lo: np.ndarray) -> None:
        mark, one, two = self.places(np.asarray(lo, np.int64), self.buckets)
        turn = 0
        for m, a, b in zip(mark.tolist(), one.tolist(), two.tolist(), strict=True):
            at = a
            for kick in range(KICKS):
                free = np.flatnonzero(self.cells[at] == 0)
                if len(free):
                    self.cells[at, free[0]] = m
                    break
                if kick == 0:
                    at = b
                    continue
                turn = (turn + 1) % SLOTS
                m, self.cells[at, turn] = int(self.cells[at, turn]), m
                at = int(self.other(at, m, self.buckets))
            else:
                self.stash.append((m << 40) | at)

    def delete(self, lo: np.ndarray) -> None:
        """Take one copy of each key's fingerprint out; keys must have been inserted."""
        mark, one, two = self.places(np.asarray(lo, np.int64), self.buckets)
        for m, a, b in zip(mark.tolist(), one.tolist(), two.tolist(), strict=True):
            for at in (a, b):
                held = np.flatnonzero(self.cells[at] == m)
                if len(held):
                    self.cells[at, held[0]] = 0
                    break
                if (m << 40) | at in self.stash:
                    self.stash.remove((m << 40) | at)
                    break

    def to_bytes(self) -> bytes:
        return struct.pack("<II", self.buckets, len(self.stash)) + np.array(self.stash, np.int64).tobytes() + self.cells.tobytes()

    @classmethod
    def from_bytes(cls, blob: bytes) -> CuckooShard:
        buckets, n = struct.unpack_from("<II", blob)
        stash = np.frombuffer(blob, np.int64, n, 8).tolist()
        return cls(buckets, np.frombuffer(blob, np.uint16, buckets * SLOTS, 8 + 8 * n).reshape(buckets, SLOTS).copy(), stash)


class ShardedProbe:
    """All shards side by side, for one vectorised lookup."""

    def __init__(self, shards: dict[int, bytes], count: int, buckets: int):
        self.count, self.buckets = count, buckets
        self.cells = np.zeros((count, buckets, SLOTS), np.uint16)
        self.stash: set[tuple[int, int]] = set()
        for k, blob in shards.items():
            shard = CuckooShard.from_bytes(blob)
            self.cells[k] = shard.cells
            self.stash |= {(k, x) for x in shard.stash}

    def hits(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        k = hi & (self.count - 1)
        mark, one, two = CuckooShard.places(lo, self.buckets)
        found = (self.cells[k, one] == mark[:, None]).any(1) | (self.cells[k, two] == mark[:, None]).any(1)
        if self.stash:
            found |= np.array([(s, (m << 40) | a) in self.stash or (s, (m << 40) | b) in self.stash for s, m, a, b in zip(k.tolist(), mark.tolist(), one.tolist(), two.tolist(), strict=True)], bool)
        return found


def _keys(text: bytes | None) -> list[tuple[int, int]]:
    return list({key_hash(k) for line in (text or b"").split(b"\n") if (k := line_key(line)) is not None})


def _rows(docs: DataFrame) -> DataFrame:
    small_batches(docs.sparkSession)
    return docs.select("doc_id", F.col("text").cast("binary").alias("text"))


def references(docs: DataFrame) -> DataFrame:
    """(hi, lo, doc_id): each key of each document once."""

    def run(batches):
        for batch in batches:
            ids, his, los = [], [], []
            for i, text in zip(batch["doc_id"].to_pylist(), batch["text"], strict=True):
                keys = _keys(text.as_py())
                ids += [i] * len(keys)
                his += [k[0] for k in keys]
                los += [k[1] for k in keys]
            yield pa.RecordBatch.from_arrays([pa.array(his, pa.int64()), pa.array(los, pa.int64()), pa.array(ids, pa.int64())], ["hi", "lo", "doc_id"])

    return _rows(docs.where("doc_id is not null")).mapInArrow(run, "hi long, lo long, doc_id long")


def _counts(refs: DataFrame) -> DataFrame:
    return refs.groupBy("hi", "lo").agg(F.min("doc_id").alias("first_doc"), F.max("doc_id").alias("last_doc"), F.count(F.lit(1)).alias("n_refs"))


def _shard_filters(shared: DataFrame, count: int, buckets: int) -> DataFrame:
    def build(part: pd.DataFrame) -> pd.DataFrame:
        shard = CuckooShard(buckets)
        shard.insert(part["lo"].to_numpy())
        return pd.DataFrame({"shard": [int(part["shard"].iloc[0])], "blob": [shard.to_bytes()]})

    return shared.select((F.col("hi").bitwiseAND(F.lit(count - 1))).cast("int").alias("shard"), "lo").groupBy("shard").applyInPandas(build, "shard int, blob binary")


@dataclass
class LineIndex:
    """Reference rows, exact counts of every key, and the filters of the shared ones."""

    refs: DataFrame
    counts: DataFrame
    filters: DataFrame
    shards: int
    buckets: int

    @classmethod
    def build(cls, docs: DataFrame) -> LineIndex:
        refs = staged(references(docs), "references")
        return cls._of(refs, staged(_counts(refs), "counts"))

    @classmethod
    def _of(cls, refs: DataFrame, counts: DataFrame) -> LineIndex:
        shared = counts.where("first_doc < last_doc")
        n = shared.count()
        shards = power_of_two(n / KEYS_PER_SHARD, 1, 2**20)
        buckets = power_of_two(2 * n / shards / SLOTS, 16, 2**24)
        return cls(refs, counts, staged(_shard_filters(shared, shards, buckets), "filters"), shards, buckets)

    def _changed(self, refs: DataFrame, counts: DataFrame, touched: DataFrame) -> LineIndex:
        """The next index: filters change only by keys of `touched` that became or ceased to be shared."""
        old = touched.join(self.counts, ["hi", "lo"], "left").select("hi", "lo", F.coalesce(F.col("first_doc") < F.col("last_doc"), F.lit(False)).alias("was"))
        new = touched.join(counts, ["hi", "lo"], "left").select("hi", "lo", F.coalesce(F.col("first_doc") < F.col("last_doc"), F.lit(False)).alias("now"))
        steps = old.join(new, ["hi", "lo"]).where("was <> now").select((F.col("hi").bitwiseAND(F.lit(self.shards - 1))).cast("int").alias("shard"), "lo", "now")
        buckets = self.buckets

        def update(held: pd.DataFrame, part: pd.DataFrame) -> pd.DataFrame:
            shard = CuckooShard.from_bytes(held["blob"].iloc[0]) if len(held) else CuckooShard(buckets)
            shard.delete(part.loc[~part["now"].astype(bool), "lo"].to_numpy(np.int64))
            shard.insert(part.loc[part["now"].astype(bool), "lo"].to_numpy(np.int64))
            k = held["shard"].iloc[0] if len(held) else part["shard"].iloc[0]
            return pd.DataFrame({"shard": [int(k)], "blob": [shard.to_bytes()]})

        filters = self.filters.groupBy("shard").cogroup(steps.groupBy("shard")).applyInPandas(update, "shard int, blob binary")
        return LineIndex(refs, counts, staged(filters, "filters"), self.shards, self.buckets)

    def insert(self, docs: DataFrame) -> LineIndex:
        """Add documents whose ids the index doesn't hold yet."""
        added = staged(references(docs), "references")
        merged = self.counts.unionByName(_counts(added)).groupBy("hi", "lo").agg(F.min("first_doc").alias("first_doc"), F.max("last_doc").alias("last_doc"), F.sum("n_refs").alias("n_refs"))
        return self._changed(staged(self.refs.unionByName(added), "references"), staged(merged, "counts"), added.select("hi", "lo").distinct())

    def delete(self, doc_ids: DataFrame) -> LineIndex:
        """Take documents out (doc_ids has doc_id); counts of their keys are made anew from the references."""
        gone = doc_ids.select("doc_id").distinct()
        touched = staged(self.refs.join(gone, "doc_id", "left_semi").select("hi", "lo").distinct(), "touched")
        refs = staged(self.refs.join(gone, "doc_id", "left_anti").select("hi", "lo", "doc_id"), "references")
        again = _counts(refs.join(touched, ["hi", "lo"], "left_semi"))
        counts = staged(self.counts.join(touched, ["hi", "lo"], "left_anti").unionByName(again), "counts")
        return self._changed(refs, counts, touched)

    def probe(self):
        """The filters in one object for all executors, or None beyond MAX_FILTER_BYTES, where sharded_hits asks them."""
        if self.shards * self.buckets * SLOTS * 2 > MAX_FILTER_BYTES:
            return None
        blobs = {r.shard: bytes(r.blob) for r in self.filters.toLocalIterator()}
        return self.refs.sparkSession.sparkContext.broadcast(ShardedProbe(blobs, self.shards, self.buckets))

    def sharded_hits(self, keys: DataFrame, most: int) -> DataFrame:
        """Rows of keys (doc_id, hi, lo) that the filters may hold, each asked in the shard of its key. most: documents of the
        most frequent key."""
        count, buckets = self.shards, self.buckets
        parts = max(1, -(-max(most, self.refs.count() // count) // KEYS_PER_GROUP))
        dealt = keys.withColumn("shard", F.col("hi").bitwiseAND(F.lit(count - 1)).cast("int")).withColumn("part", F.pmod(F.xxhash64("doc_id"), F.lit(parts)).cast("int"))
        every = self.filters.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))

        def ask(rows: pa.Table, held: pa.Table) -> pa.Table:
            slim = rows.select(["doc_id", "hi", "lo"])
            if not held.num_rows:
                return slim.slice(0, 0)
            probe = ShardedProbe({0: held["blob"][0].as_py()}, 1, buckets)
            return slim.filter(pa.array(probe.hits(np.zeros(slim.num_rows, np.int64), slim["lo"].to_numpy())))

        return dealt.groupBy("shard", "part").cogroup(every.groupBy("shard", "part")).applyInArrow(ask, "doc_id long, hi long, lo long")

    def apply(self, docs: DataFrame) -> DataFrame:
        """doc_id, n_lines, n_dropped, kept_sha256 and kept (binary) of each row of docs."""
        probe = self.probe()
        rows = _rows(docs)

        def possible(texts: list) -> tuple[np.ndarray, list[np.ndarray]]:
            """The keys of a batch that the filters may hold, and each text's places among them."""
            keys = [_keys(t.as_py()) for t in texts]
            ends = np.cumsum([len(k) for k in keys])
            flat = np.array([k for ks in keys for k in ks], np.int64).reshape(-1, 2)
            hit = np.ones(len(flat), bool) if probe is None or not len(flat) else probe.value.hits(flat[:, 0], flat[:, 1])
            return flat, [np.flatnonzero(h) + e - len(h) for h, e in zip(np.split(hit, ends[:-1]), ends, strict=True)] if len(keys) else []

        def hit_rows(batches):
            for batch in batches:
                flat, at = possible(batch["text"])
                ids = [i for i, a in zip(batch["doc_id"].to_pylist(), at, strict=True) for _ in range(len(a))]
                took = flat[np.concatenate(at).astype(np.int64)] if at else flat
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(took[:, 0]), pa.array(took[:, 1])], ["doc_id", "hi", "lo"])

        @F.pandas_udf("boolean")
        def may_hit(texts: pd.Series) -> pd.Series:
            return pd.Series([len(a) > 0 for a in possible(pa.array(texts, pa.binary()))[1]], dtype=bool)

        def cut(batches):
            for batch in batches:
                n, dropped, shas, kept = [], [], [], []
                for text, gone in zip(batch["text"], batch["gone"], strict=True):
                    lines = (text.as_py() or b"").split(b"\n")
                    out = {(g["hi"], g["lo"]) for g in gone.as_py() or ()}
                    left = lines if not out else [x for x in lines if (k := line_key(x)) is None or key_hash(k) not in out]
                    n.append(len(lines))
                    dropped.append(len(lines) - len(left))
                    kept.append(b"\n".join(left))
                    shas.append(hashlib.sha256(kept[-1]).hexdigest())
                yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(n, pa.int64()), pa.array(dropped, pa.int64()), pa.array(shas, pa.string()), pa.array(kept, pa.binary())], ["doc_id", "n_lines", "n_dropped", "kept_sha256", "kept"])

        shared = self.counts.where("first_doc < last_doc").select("hi", "lo", "first_doc", "n_refs")
        total, most = shared.agg(F.coalesce(F.sum("n_refs"), F.lit(0)), F.coalesce(F.max("n_refs"), F.lit(0))).first()
        hits = rows.where("doc_id is not null").mapInArrow(hit_rows, "doc_id long, hi long, lo long")
        hits = staged(hits if probe is not None else self.sharded_hits(hits, most), "hits")
        found = join_by_weight(hits, shared, ["hi", "lo"], "n_refs", total).where("first_doc < doc_id")
        gone = found.groupBy("doc_id").agg(F.collect_set(F.struct("hi", "lo")).alias("gone"))
        form = "doc_id long, n_lines long, n_dropped long, kept_sha256 string, kept binary"
        if probe is None:  # only the shards know which documents are hit
            return rows.join(gone, "doc_id", "left").select(F.col("doc_id").cast("long").alias("doc_id"), "text", "gone").mapInArrow(cut, form)
        flagged = rows.withColumn("flag", F.coalesce(may_hit("text"), F.lit(False)) & F.col("doc_id").isNotNull())
        empty = F.lit(None).cast("array<struct<hi:bigint,lo:bigint>>").alias("gone")
        met = flagged.where("flag").join(gone, "doc_id", "left").select("doc_id", "text", "gone")
        passed = flagged.where("not flag").select("doc_id", "text", empty)
        return reduce(DataFrame.unionByName, [x.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "gone").mapInArrow(cut, form) for x in (met, passed)])


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return LineIndex.build(docs).apply(docs).select("doc_id", "n_lines", "n_dropped", "kept_sha256")


OP9_SQL = r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS line_no
  FROM documents),
keyed AS (SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM lines),
shared AS (SELECT key, min(doc_id) AS first_doc FROM keyed WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) >= 2),
judged AS (SELECT k.*, s.first_doc IS NULL OR s.first_doc = k.doc_id AS stays FROM keyed k LEFT JOIN shared s USING (key))
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE NOT stays) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY line_no) FILTER (WHERE stays), '')) AS kept_sha256
FROM judged GROUP BY doc_id
"""
