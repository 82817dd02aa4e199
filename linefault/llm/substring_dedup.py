"""Substring deduplication with sharded suffix arrays built by induced sorting.

A byte goes if it is covered by a LENGTH-byte string that also starts in a document with a smaller doc_id.
Every such string is dealt to a shard by its anchor, the least hash of the GRAM-byte strings inside it, so equal
strings meet in one shard wherever they stand, and consecutive strings with one anchor travel as
one segment of text. Two documents that share a string agree on WING more bytes to the left or to the right of its
anchor, so a first pass finds the wings (anchor and WING bytes on one side) that more than one document may hold, and
keeps them in a filter of bounded size; only segments with such a wing are shuffled, each distinct one once per batch
with the places where it stands. A shard concatenates its distinct segments, sorts their suffixes by induced
sorting, reads off the permuted common prefixes, and so finds for each string the smallest document that holds it.
The ranges to remove go back to the documents.

Defined cases: null text is empty; texts shorter than LENGTH lose nothing; rows with a null doc_id lose nothing and
remove nothing; rows with equal doc_id don't remove from each other; an empty table gives an empty
result; only id and text are read.
"""

from __future__ import annotations

import hashlib
import struct

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import power_of_two, small_batches, staged, table
from .suffix_array import permuted_common_prefixes, suffix_array

LENGTH, GRAM = 50, 20
SPAN = LENGTH - GRAM + 1
#: Of LENGTH - GRAM further bytes of a shared string at least half lie on one side of the anchor.
WING = (LENGTH - GRAM) // 2
SEED = 11
#: Bytes of input for each bucket of wings, shard of segments and group of documents.
BUCKET_BYTES, SHARD_BYTES, GROUP_BYTES = 2**24, 2**22, 2**24
#: The wing filter has at most this many bits (32 MB); beyond about 4 GB of input more segments without a
#: partner reach the shards, which drop them.
MAX_FILTER_BITS = 2**28
#: Documents handled at once in a worker.
BATCH, BATCH_BYTES = 4096, 2**24

_rng = np.random.default_rng(SEED)
_LETTERS = _rng.integers(0, 2**64, 256, dtype=np.uint64)
_BASE = int(_rng.integers(0, 2**63)) * 2 + 1
_POWER = [np.uint64(pow(_BASE, k, 2**64)) for k in range(64)]
_MIX = np.uint64(0x9E3779B97F4A7C15)
#: Positions take the low bits of a sliding minimum, so texts are cut into parts of fewer bytes than this.
_PLACE_BITS = 24
_PLACE = np.uint64(2**_PLACE_BITS - 1)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * _MIX
    return x ^ (x >> np.uint64(29))


def segments(text: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(anchor, first, last, wings) of each run of consecutive LENGTH-byte strings with one anchor.

    first and last are the starts of the run's first and last string. wings has two hashes a run, of the anchor
    with WING bytes to its left and to its right; 0 where the text ends before.
    """
    parts = []
    step = 2**_PLACE_BITS - 2 * LENGTH
    for at in range(0, max(1, len(text) - LENGTH + 1), step):
        lead = min(at, WING)  # so that wings look the same wherever a text is cut
        found = _segments(text[at - lead : at + step + LENGTH - 1 + WING], lead, min(step, len(text) - LENGTH + 1 - at))
        parts.append((found[0], found[1] + at - lead, found[2] + at - lead, found[3]))
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True)) if len(parts) > 1 else parts[0]


def _segments(text: bytes, lead: int, count: int):
    """segments of the `count` strings that start at lead, lead + 1, ..."""
    raw = np.frombuffer(text, np.uint8)
    n = len(raw)
    if count <= 0 or n < LENGTH:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, 2), np.uint64)
    h = {1: _LETTERS[raw]}
    for k in (1, 2, 4, 8):  # hashes of 2, 4, 8 and 16 bytes from halves
        h[2 * k] = h[k][:-k] * _POWER[k] + h[k][k:]
    gram = _mixed(h[16][: n - GRAM + 1] * _POWER[4] + h[4][16:])
    least, have = (gram & ~_PLACE) | np.arange(len(gram), dtype=np.uint64), 1
    while 2 * have <= SPAN:
        least = np.minimum(least[:-have], least[have:])
        have *= 2
    rest = SPAN - have
    place = (np.minimum(least[: len(least) - rest], least[rest:])[lead : lead + count] & _PLACE).astype(np.int64)
    first = np.concatenate([[0], np.flatnonzero(place[1:] != place[:-1]) + 1])
    last = np.append(first[1:], len(place)) - 1
    place = place[first]
    # Wings of GRAM + WING = 35 bytes, from hashes of 16, 16, 2 and 1.
    wings = np.zeros((len(place), 2), np.uint64)
    for side, at in enumerate((place - WING, place)):
        ok = (at >= 0) & (at + GRAM + WING <= n)
        q = at[ok]
        wings[ok, side] = _mixed(h[16][q] * _POWER[19] + h[16][q + 16] * _POWER[3] + h[2][q + 32] * _POWER[1] + h[1][q + 34] + np.uint64(side)) | np.uint64(2**_PLACE_BITS)
    return gram[place], first + lead, last + lead, wings & ~_PLACE


def _rows(docs: DataFrame) -> DataFrame:
    small_batches(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text"))


def _slices(batches):
    """Arrow batches gathered to BATCH rows or BATCH_BYTES, whichever comes first."""
    held, rows, size = [], 0, 0
    for batch in batches:
        held.append(batch)
        rows, size = rows + batch.num_rows, size + batch.nbytes
        if rows >= BATCH or size >= BATCH_BYTES:
            yield pa.concat_batches(held)
            held, rows, size = [], 0, 0
    if held:
        yield pa.concat_batches(held)


class WingFilter:
    """Two bits for each wing that may be shared. The buckets of wings own its parts, in order."""

    def __init__(self, bits: int, buckets: int):
        self.bits, self.buckets = bits, buckets
        self.per = bits // buckets

    def bucket(self, wings: np.ndarray) -> np.ndarray:
        return (wings >> np.uint64(64 - self.buckets.bit_length() + 1)).astype(np.int64) if self.buckets > 1 else np.zeros(len(wings), np.int64)

    def places(self, wings: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Both bits of each wing inside its bucket's part."""
        own = _mixed(wings)
        return (own & np.uint64(self.per - 1)).astype(np.int64), ((own >> np.uint64(32)) & np.uint64(self.per - 1)).astype(np.int64)

    def part(self, wings: np.ndarray) -> bytes:
        flags = np.zeros(self.per, bool)
        for at in self.places(wings):
            flags[at] = True
        return np.packbits(flags, bitorder="little").tobytes()

    def holds(self, parts: np.ndarray, wings: np.ndarray) -> np.ndarray:
        base = self.bucket(wings) * self.per
        found = wings > 0
        for at in self.places(wings):
            at = at + base
            found &= (parts[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
        return found


def _squeezed(keys: np.ndarray) -> bytes:
    """Sorted keys as compressed differences, byte by byte."""
    steps = np.diff(keys, prepend=np.uint64(0)) >> np.uint64(_PLACE_BITS)
    return zstandard.ZstdCompressor(level=1).compress(steps.view(np.uint8).reshape(-1, 8).T.tobytes())


def _loosened(blob: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(blob), np.uint8)
    return np.cumsum(np.ascontiguousarray(planes.reshape(8, -1).T).view(np.uint64).ravel(), dtype=np.uint64) << np.uint64(_PLACE_BITS)


def shared_wings(docs: DataFrame, filter_: WingFilter) -> np.ndarray:
    """The filter's bytes. Each batch sends its distinct wings, and those of several of its documents
    twice; a wing that a bucket receives twice may be shared."""

    def send(batches):
        for batch in _slices(batches):
            found = [np.unique(segments(t.as_py())[3]) for t in batch["text"]]
            wings = np.sort(np.concatenate(found)) if found else np.zeros(0, np.uint64)
            wings = wings[wings > 0]
            third = np.zeros(len(wings), bool)
            third[2:] = wings[2:] == wings[:-2]
            wings = wings[~third]
            bucket = filter_.bucket(wings)  # in order, as the wings are
            cuts = np.flatnonzero(np.diff(bucket)) + 1
            names = bucket[np.concatenate([[0], cuts])] if len(bucket) else bucket
            parts = [_squeezed(p) for p in np.split(wings, cuts)] if len(bucket) else []
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(parts, pa.binary())], ["bucket", "wings"])

    def repeated(part: pa.Table) -> pa.Table:
        wings = np.sort(np.concatenate([_loosened(x.as_py()) for x in part["wings"]]))
        again = np.unique(wings[1:][wings[1:] == wings[:-1]])
        return pa.table({"bucket": pa.array([part["bucket"][0].as_py()], pa.int64()), "bits": pa.array([filter_.part(again)], pa.binary())})

    parts = _rows(docs).where("doc_id is not null").mapInArrow(send, "bucket long, wings binary").groupBy("bucket").applyInArrow(repeated, "bucket long, bits binary")
    out = np.zeros(filter_.bits // 8, np.uint8)
    size = filter_.per // 8
    for row in parts.toLocalIterator():  # filter_.bits in all
        out[row.bucket * size : (row.bucket + 1) * size] = np.frombuffer(row.bits, np.uint8)
    return out


_HEAD = struct.Struct("<III")


def _pack(ids, keys, places, anchors, texts) -> bytes:
    """A batch's share of one shard: documents, places (document, first string, segment), and segments."""
    sizes = np.array([len(t) for t in texts], "<u4")
    body = b"".join([_HEAD.pack(len(ids), len(places), len(texts)), np.asarray(ids, "<i8").tobytes(), np.asarray(keys, "<i8").tobytes(), np.asarray(places, "<u4").tobytes(), np.asarray(anchors, "<u8").tobytes(), sizes.tobytes(), *texts])
    return zstandard.ZstdCompressor(level=1).compress(body)


def _unpack(blob: bytes):
    body = zstandard.ZstdDecompressor().decompress(blob)
    docs, n, m = _HEAD.unpack_from(body)
    at = _HEAD.size
    ids = np.frombuffer(body, "<i8", docs, at)
    keys = np.frombuffer(body, "<i8", docs, at + 8 * docs)
    at += 16 * docs
    places = np.frombuffer(body, "<u4", 3 * n, at).reshape(n, 3).astype(np.int64)
    at += 12 * n
    anchors = np.frombuffer(body, "<u8", m, at)
    sizes = np.frombuffer(body, "<u4", m, at + 8 * m)
    ends = np.cumsum(sizes, dtype=np.int64) + at + 12 * m
    return ids, keys, places, anchors, [body[e - s : e] for e, s in zip(ends.tolist(), sizes.tolist(), strict=True)]


def text_key(text: bytes) -> int:
    return xxhash.xxh3_64_intdigest(text) - 2**63


def candidate_segments(docs: DataFrame, filter_: WingFilter, parts, shards: int) -> DataFrame:
    """(shard, blob): what each batch holds of each shard."""

    def send(batches):
        for batch in _slices(batches):
            ids = batch["doc_id"].to_pylist()
            per: dict[int, tuple] = {}
            for i, item in zip(ids, batch["text"], strict=True):
                text = item.as_py()
                anchors, first, last, wings = segments(text)
                if not len(anchors):
                    continue
                keep = filter_.holds(parts.value, wings.ravel()).reshape(-1, 2).any(axis=1)
                if not keep.any():
                    continue
                anchors, first, last = anchors[keep], first[keep], last[keep]
                key = text_key(text)
                for shard, anchor, a, b in zip((anchors & np.uint64(shards - 1)).tolist(), anchors.tolist(), first.tolist(), last.tolist(), strict=True):
                    if (own := per.get(shard)) is None:
                        own = per[shard] = ([], [], [], {}, [])
                    if not own[0] or own[1][-1] != key or own[0][-1] != i:
                        own[0].append(i)
                        own[1].append(key)
                    piece = text[a : b + LENGTH]
                    at = own[3].setdefault(piece, len(own[3]))
                    if at == len(own[4]):
                        own[4].append(anchor)
                    own[2].append((len(own[0]) - 1, a, at))
            blobs = [_pack(d, k, p, a, list(t)) for d, k, p, t, a in per.values()]
            yield pa.RecordBatch.from_arrays([pa.array(list(per), pa.int64()), pa.array(blobs, pa.binary())], ["shard", "blob"])

    return _rows(docs).where("doc_id is not null").mapInArrow(send, "shard long, blob binary")


def smallest_documents(texts: list[bytes], owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For the strings of distinct segments, each owned by a smallest document: (first, smallest), where
    first[j] is where the strings of segment j begin in `smallest`."""
    joined = b"\x00".join(texts)
    sizes = np.array([len(t) for t in texts], np.int64)
    begin = np.cumsum(sizes + 1) - sizes - 1
    strings = sizes - LENGTH + 1
    first = np.cumsum(strings) - strings
    starts = np.repeat(begin - first, strings) + np.arange(int(strings.sum()))
    order = suffix_array(np.frombuffer(joined, np.uint8))
    prefix = permuted_common_prefixes(joined, order, LENGTH)
    valid = np.zeros(len(joined), bool)
    valid[starts] = True
    holder = np.zeros(len(joined), np.int64)
    holder[starts] = np.repeat(owner, strings)
    order = order[valid[order]]
    # A string equals the one before it if the whole prefix agrees; its predecessor then begins a string as well.
    heads = np.flatnonzero(prefix[order] < LENGTH) if len(order) else np.zeros(0, np.int64)
    if len(order) and (not len(heads) or heads[0] != 0):
        heads = np.concatenate([[0], heads])
    least = np.minimum.reduceat(holder[order], heads) if len(order) else holder[:0]
    out = np.empty(len(joined), np.int64)
    out[order] = np.repeat(least, np.diff(np.append(heads, len(order))))
    return first, out[starts]


def _shard_ranges(part: pa.Table, groups: int) -> pa.Table:
    """(group, blob): the ranges that one shard removes, as (doc_id, text key, begin, end), by document group."""
    found: dict[bytes, int] = {}
    anchor_of: list[int] = []
    rows = []
    for item in part["blob"]:
        ids, keys, places, anchors, texts = _unpack(item.as_py())
        name = np.empty(len(texts), np.int64)
        for j, (t, a) in enumerate(zip(texts, anchors.tolist(), strict=True)):
            name[j] = at = found.setdefault(t, len(found))
            if at == len(anchor_of):
                anchor_of.append(a)
        rows.append(np.column_stack([ids[places[:, 0]], keys[places[:, 0]], places[:, 1], name[places[:, 2]]]))
    empty = pa.table({"group": pa.array([], pa.int64()), "blob": pa.array([], pa.binary())})
    if not rows:
        return empty
    doc, key, begin, name = np.concatenate(rows).T
    count = len(found)
    low, high = np.full(count, np.iinfo(np.int64).max), np.full(count, np.iinfo(np.int64).min)
    np.minimum.at(low, name, doc)
    np.maximum.at(high, name, doc)
    # Anchors of a single document have no partner: their segments drop out here.
    anchor = np.unique(np.array(anchor_of, np.uint64), return_inverse=True)[1]
    a_low, a_high = np.full(anchor.max() + 1, np.iinfo(np.int64).max), np.full(anchor.max() + 1, np.iinfo(np.int64).min)
    np.minimum.at(a_low, anchor, low)
    np.maximum.at(a_high, anchor, high)
    shared = (a_low < a_high)[anchor]
    if not shared.any():
        return empty
    texts = [t for t, s in zip(found, shared.tolist(), strict=True) if s]
    first, least = smallest_documents(texts, low[shared])
    size = np.array([len(t) for t in texts]) - LENGTH + 1
    place = np.cumsum(shared) - 1
    use = shared[name]
    doc, key, begin, seg = doc[use], key[use], begin[use], place[name[use]]
    # Where a segment stands in a document after its owner, all its strings go.
    later = doc > low[shared][seg]
    out = [np.column_stack([doc[later], key[later], begin[later], begin[later] + size[seg[later]] - 1 + LENGTH])]
    gone = least < np.repeat(low[shared], size)
    touched = np.flatnonzero(np.add.reduceat(gone, first) > 0) if len(first) else first
    of = {int(j): np.flatnonzero(gone[first[j] : first[j] + size[j]]) for j in touched}
    for d, k, b, j in zip(doc[~later].tolist(), key[~later].tolist(), begin[~later].tolist(), seg[~later].tolist(), strict=True):
        if j in of:  # runs of strings that a smaller document holds
            at = of[j]
            cut = np.flatnonzero(np.diff(at) > 1)
            a, e = at[np.concatenate([[0], cut + 1])], at[np.append(cut, len(at) - 1)]
            out.append(np.column_stack([np.full(len(a), d), np.full(len(a), k), b + a, b + e + LENGTH]))
    ranges = np.concatenate(out).astype("<i8")
    group = group_of(ranges[:, 0], groups)
    order = np.argsort(group, kind="stable")
    ranges, group = ranges[order], group[order]
    cuts = np.flatnonzero(np.diff(group)) + 1
    blobs = [zstandard.ZstdCompressor(level=1).compress(p.tobytes()) for p in np.split(ranges, cuts)] if len(ranges) else []
    return pa.table({"group": pa.array(group[np.concatenate([[0], cuts])] if len(group) else group, pa.int64()), "blob": pa.array(blobs, pa.binary())})


def group_of(ids: np.ndarray, groups: int) -> np.ndarray:
    mixed = (ids.astype(np.uint64) * _MIX) >> np.uint64(40)
    return (mixed & np.uint64(groups - 1)).astype(np.int64)


def remove(text: bytes, ranges: np.ndarray) -> tuple[int, int, bytes]:
    """(bytes removed, maximal runs removed, what is left)."""
    if not len(ranges):
        return 0, 0, text
    edge = np.zeros(len(text) + 1, np.int64)
    np.add.at(edge, ranges[:, 0], 1)
    np.add.at(edge, ranges[:, 1], -1)
    gone = np.cumsum(edge[:-1]) > 0
    runs = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum())
    return int(gone.sum()), runs, np.frombuffer(text, np.uint8)[~gone].tobytes()


def remove_repeats(docs: DataFrame, max_bits: int = MAX_FILTER_BITS) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept (binary)."""
    spark = docs.sparkSession
    rows = _rows(docs)
    total = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    buckets = power_of_two(total / BUCKET_BYTES, 16, 2**20)
    shards = power_of_two(total / SHARD_BYTES, 16, 2**24)
    groups = power_of_two(total / GROUP_BYTES, 16, 2**23)
    filter_ = WingFilter(power_of_two(total / 14, max(2**16, 64 * buckets), max(max_bits, 64 * buckets)), buckets)
    parts = spark.sparkContext.broadcast(shared_wings(docs, filter_))
    dealt = candidate_segments(docs, filter_, parts, shards)
    ranges = dealt.groupBy("shard").applyInArrow(lambda part: _shard_ranges(part, groups), "group long, blob binary")

    def label(batches):
        for batch in batches:
            ids = batch["doc_id"].fill_null(-1).to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([pa.array(group_of(ids, groups), pa.int64()), batch["doc_id"], batch["text"]], ["group", "doc_id", "text"])

    named = rows.mapInArrow(label, "group long, doc_id long, text binary")

    def finish(texts: pa.Table, removed: pa.Table) -> pa.Table:
        raw = b"".join(zstandard.ZstdDecompressor().decompress(x.as_py()) for x in removed["blob"])
        found = np.frombuffer(raw, "<i8").reshape(-1, 4)
        found = found[np.lexsort((found[:, 1], found[:, 0]))]
        heads = np.flatnonzero(np.concatenate([[True], (np.diff(found[:, :2], axis=0) != 0).any(axis=1)])) if len(found) else np.zeros(0, np.int64)
        of = {(int(found[a, 0]), int(found[a, 1])): found[a:b, 2:] for a, b in zip(heads, np.append(heads[1:], len(found))[: len(heads)], strict=True)}
        out: dict[str, list] = {k: [] for k in ("n_bytes", "n_removed", "n_spans", "kept_sha256", "kept")}
        none = np.zeros((0, 2), np.int64)
        for i, item in zip(texts["doc_id"].to_pylist(), texts["text"], strict=True):
            text = item.as_py()
            n, runs, kept = remove(text, of.get((i, text_key(text)), none) if i is not None else none)
            for k, v in zip(out, (len(text), n, runs, hashlib.sha256(kept).hexdigest(), kept), strict=True):
                out[k].append(v)
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
        return pa.table({"doc_id": texts["doc_id"], **{k: pa.array(v, t) for (k, v), t in zip(out.items(), kinds, strict=True)}})

    form = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"
    return named.groupBy("group").cogroup(staged(ranges, "ranges").groupBy("group")).applyInArrow(finish, form)


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents")).drop("kept")
