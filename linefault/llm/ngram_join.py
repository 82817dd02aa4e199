"""N-gram Jaccard join by MinHash banding, verified on full n-gram sets.

Equal texts are one node. Every node's word n-grams give a MinHash signature, cut into bands whose
number and width follow from the similarity and the target recall. Nodes meet by band hash. Inside a bucket
each node is compared with the bucket's hub (the node that meets most others), not with all; the verified
links give components. Where a bucket then still holds nodes of different components, its pairs across components
are looked at as well, so a bucket whose nodes are one class costs one comparison a node. These pairs first meet in
blocks, on one-permutation sketches: a pair goes on to its full sets unless its estimate lies more than MARGIN standard
deviations below the similarity, and only in the first band it shares. Pairs whose n-gram counts differ by more than the
similarity allows are left out, which is exact.

The number of links of a document needs every pair of its component, not only those that connect it: the nodes of each
component are compared all with all on their full n-gram sets, in pairs of tiles, and only the sums leave a block.

Words are runs of non-blank bytes ([^\\x20\\x09-\\x0D]+), as they are. A text of fewer than n words has its whole
word sequence as its only n-gram; a text without words has none and is linked to equal texts only.

Defined cases: null text is empty; repeated rows are copies of one text; a null doc_id is kept as a row and
counts as largest when the class is named; an empty table gives an empty result; extra columns are kept.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import columns_of, fresh, power_of_two, small_batches, staged, table
from .graph import connected_components

N, SIMILARITY, RECALL, MOST_HASHES = 5, 0.8, 0.9999, 128
SEED = 7
#: Bins of the sketch (one permutation, the least n-gram hash of each bin, 16 bits of it), and how many standard
#: deviations below the similarity an estimate may lie.
SKETCH_BITS, MARGIN = 9, 4.5
SKETCH = 2**SKETCH_BITS
#: Nodes of a bucket that meet in one block; larger buckets are cut into tiles that meet in pairs.
TILE = 4096
#: Bucket rows that one group of blocks holds on average.
GROUP_ROWS = 2000
#: Nodes and n-grams that one tile of a component holds on average, when its links are counted.
LINK_TILE, LINK_GRAMS = 1024, 2**18
#: n-grams hashed at once, so that very long texts need bounded memory.
CHUNK = 4096
#: Bits of the filter that spares texts of no pair the shuffle; fixed, so the broadcast is bounded.
FILTER_BITS = 2**26
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True


def choose_bands(similarity: float = SIMILARITY, recall: float = RECALL, most: int = MOST_HASHES) -> tuple[int, int]:
    """(bands, rows): the widest bands that find a pair at `similarity` with `recall` within `most` hashes."""
    found = None
    for rows in range(1, most + 1):
        chance = similarity**rows
        bands = 1 if chance >= 1 else math.ceil(math.log(1 - recall) / math.log1p(-chance))
        if bands * rows <= most:
            found = (bands, rows)
    if found is None:
        raise ValueError("the target recall needs more hashes")
    return found


class Hasher:
    """Word, n-gram and band hashes in numpy."""

    def __init__(self, n: int, bands: int, rows: int, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.n, self.bands, self.rows = n, bands, rows
        self.letters = rng.integers(0, 2**64, 256, dtype=np.uint64)
        self.base, self.step, self.mix = rng.integers(0, 2**63, 3, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.powers = np.ones(64, np.uint64)
        self.mult = rng.integers(0, 2**63, bands * rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.add = rng.integers(0, 2**64, bands * rows, dtype=np.uint64)
        self.join = rng.integers(0, 2**63, rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

    def ngrams(self, text: bytes) -> np.ndarray:
        """Sorted distinct n-gram hashes."""
        raw = np.frombuffer(text, np.uint8)
        word = ~_BLANK[raw]
        starts = np.flatnonzero(word & ~np.concatenate([[False], word[:-1]])) if len(raw) else np.zeros(0, np.int64)
        if not len(starts):
            return np.zeros(0, np.uint64)
        place = np.arange(len(raw)) - np.repeat(starts, np.diff(np.append(starts, len(raw)))) if starts[0] == 0 else np.arange(len(raw)) - np.concatenate([np.zeros(starts[0], np.int64), np.repeat(starts, np.diff(np.append(starts, len(raw))))])
        longest = int(place.max()) + 1
        if longest > len(self.powers):
            with np.errstate(over="ignore"):
                self.powers = np.cumprod(np.concatenate([[np.uint64(1)], np.full(2 * longest, self.base, np.uint64)]), dtype=np.uint64)
        elif self.powers[1] == 1:
            self.powers = np.cumprod(np.concatenate([[np.uint64(1)], np.full(63, self.base, np.uint64)]), dtype=np.uint64)
        words = np.add.reduceat(np.where(word, self.letters[raw] * self.powers[place], np.uint64(0)), starts)
        words = self._mixed(words)
        count = max(1, len(words) - self.n + 1)
        grams = words[:count].copy()
        for j in range(1, min(self.n, len(words))):
            grams = grams * self.step + words[j : j + count]
        return np.unique(self._mixed(grams))

    def _mixed(self, x: np.ndarray) -> np.ndarray:
        x = (x ^ (x >> np.uint64(31))) * self.mix
        return x ^ (x >> np.uint64(29))

    def band_hashes(self, grams: np.ndarray) -> tuple[np.ndarray, bytes]:
        """The hash of each band, and the sketch: 16 bits of the least hash of each bin, 0 for an empty bin."""
        least = np.full(len(self.mult), np.iinfo(np.uint64).max, np.uint64)
        for i in range(0, len(grams), CHUNK):
            part = grams[i : i + CHUNK, None] * self.mult[None, :] + self.add[None, :]
            least = np.minimum(least, part.min(axis=0))
        least = self._mixed(least)
        bands = self._mixed((least.reshape(self.bands, self.rows) * self.join[None, :]).sum(axis=1, dtype=np.uint64))
        bins = grams >> np.uint64(64 - SKETCH_BITS)
        first = np.flatnonzero(np.concatenate([[True], bins[1:] != bins[:-1]]))  # grams are sorted
        sketch = np.zeros(SKETCH, "<u2")
        sketch[bins[first].astype(np.int64)] = (grams[first] & np.uint64(0xFFFF)) | np.uint64(1)
        return bands.astype(np.int64), sketch.tobytes()


def ngram_set(text: bytes, n: int = N) -> set:
    words = text.split()
    if len(words) < n:
        return {tuple(words)} if words else set()
    return set(zip(*[words[i:] for i in range(n)], strict=False))


def jaccard(a: set, b: set) -> float:
    both = len(a & b)
    return both / (len(a) + len(b) - both) if both else 0.0


def _texts(docs: DataFrame, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("binary"), F.lit(b""))
    return docs.select(F.unhex(F.md5(text)).alias("node"), text.alias("text"))


def signatures(docs: DataFrame, n: int, bands: int, rows: int, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """(doc_id, node, grams, hashes, sketch) of every document."""

    def run(batches):
        hasher = Hasher(n, bands, rows)
        for batch in batches:
            counts, hashes, sketches = [], [], []
            for text in batch["text"]:
                grams = hasher.ngrams(text.as_py())
                counts.append(len(grams))
                band, sketch = hasher.band_hashes(grams) if len(grams) else (np.zeros(0, np.int64), b"")
                hashes.append(band)
                sketches.append(sketch)
            ends = np.concatenate([[0], np.cumsum([len(h) for h in hashes])]).astype(np.int32)
            flat = np.concatenate(hashes) if hashes else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["node"], pa.array(counts, pa.int64()), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat, pa.int64())), pa.array(sketches, pa.binary())], ["doc_id", "node", "grams", "hashes", "sketch"])

    small_batches(docs.sparkSession)
    text = F.coalesce(F.col(text_col).cast("binary"), F.lit(b""))
    rows_ = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.unhex(F.md5(text)).alias("node"), text.alias("text"))
    return rows_.mapInArrow(run, "doc_id long, node binary, grams long, hashes array<long>, sketch binary")


def _own_texts(ends: DataFrame, texts: DataFrame) -> DataFrame:
    """(node, text) of the distinct nodes of `ends`. Other texts are left out map-side by a filter of fixed size,
    then by the join."""
    words = power_of_two(ends.count() * 16, 2**12, FILTER_BITS) // 64
    place = lambda h: (F.pmod(h, F.lit(words)), F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(h, 58).cast("int")))
    word, bit = place(F.xxhash64("node"))
    bloom = ends.select(word.alias("word"), bit.alias("bit")).groupBy("word").agg(F.bit_or("bit").alias("bits"))
    some = texts.join(F.broadcast(bloom), word == F.col("word")).where(F.col("bits").bitwiseAND(bit) != 0).select("node", "text")
    # ends are distinct; a semi join would be pushed below the filter.
    return some.join(ends, "node").groupBy("node").agg(F.first("text").alias("text"))


def _near(pairs: DataFrame, texts: DataFrame, n: int, similarity: float) -> DataFrame:
    """The pairs (a, b) whose full n-gram sets reach the similarity."""
    ends = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()
    own = _own_texts(ends, texts)
    one = own.select(F.col("node").alias("a"), F.col("text").alias("text_a"))
    two = own.select(F.col("node").alias("b"), F.col("text").alias("text_b"))

    def run(batches):
        last, held = None, set()
        for batch in batches:
            keep = []
            for i in range(batch.num_rows):
                b = batch["b"][i].as_py()
                if b != last:
                    last, held = b, ngram_set(batch["text_b"][i].as_py(), n)
                keep.append(jaccard(ngram_set(batch["text_a"][i].as_py(), n), held) >= similarity)
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return pairs.join(one, "a").join(two, "b").select("a", "b", "text_a", "text_b").mapInArrow(run, "a binary, b binary")


def may_reach(one: np.ndarray, two: np.ndarray, grams: np.ndarray, similarity: float) -> np.ndarray:
    """Whether the estimate from two rows of sketches may come from a pair at the similarity, given both numbers of n-grams
    together: its variance is that of drawing the filled bins without replacement from the union of both sets."""
    filled = np.maximum(((one | two) != 0).sum(axis=1), 1)
    agree = ((one == two) & (one != 0)).sum(axis=1)
    union = np.maximum(grams / (1 + similarity), filled + 1.0)
    spread = np.sqrt(similarity * (1 - similarity) * np.maximum((1 + 1 / (union - 1)) / filled - 1 / (union - 1), 0))
    return agree >= (similarity - MARGIN * spread - 0.01) * filled


def _across(part: pd.DataFrame, similarity: float) -> pd.DataFrame:
    """Pairs of different components in the buckets of one group that their sketches don't rule out."""
    out: list[tuple] = []
    for (band, _, low, high), rows in part.groupby(["band", "hash", "low", "high"], sort=False):
        if rows["root"].nunique() < 2:
            continue
        node, grams = rows["node"].to_numpy(), rows["grams"].to_numpy()
        root = pd.factorize(rows["root"])[0]
        sketch = np.frombuffer(b"".join(rows["sketch"]), "<u2").reshape(len(rows), SKETCH)
        earlier = np.stack(rows["hashes"].to_list())[:, :band]
        tile = rows["tile"].to_numpy()
        one, two = np.flatnonzero(tile == low), np.flatnonzero(tile == high)
        step = max(1, 2**21 // max(1, len(two)))
        for at in range(0, len(one), step):
            i = one[at : at + step]
            a, b = grams[i][:, None], grams[two][None, :]
            may = (root[i][:, None] != root[two][None, :]) & (np.minimum(a, b) >= similarity * np.maximum(a, b))
            if low == high:
                may &= i[:, None] < two[None, :]
            x, y = np.nonzero(may)
            x, y = i[x], two[y]
            for cut in range(0, len(x), 2**13):  # sketches and earlier bands of what is left, in pieces
                p, q = x[cut : cut + 2**13], y[cut : cut + 2**13]
                like = may_reach(sketch[p], sketch[q], grams[p] + grams[q], similarity)
                p, q = p[like], q[like]
                new = ~(earlier[p] == earlier[q]).any(axis=1)
                out += zip(node[p[new]], node[q[new]], strict=True)
    pairs = [(max(a, b), min(a, b)) for a, b in out]
    return pd.DataFrame(pairs, columns=["a", "b"])


def similar_links(signed: DataFrame, texts: DataFrame, n: int = N, similarity: float = SIMILARITY) -> tuple[DataFrame, DataFrame]:
    """Verified links (a, b) and components (node, root) of the nodes of `signed` (node, grams, hashes, sketch)."""
    nodes = signed.groupBy("node").agg(F.first("grams").alias("grams"), F.first("hashes").alias("hashes"), F.first("sketch").alias("sketch"))
    met = nodes.select("node", "grams", F.posexplode("hashes").alias("band", "hash"))
    shared = met.groupBy("band", "hash").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    buckets = staged(met.join(shared, ["band", "hash"]), "buckets")
    meets = buckets.groupBy("node").agg(F.sum("n").alias("meets"))
    rated = buckets.join(meets, "node")
    hubs = rated.groupBy("band", "hash").agg(F.max(F.struct("meets", "node", "grams")).alias("hub")).select("band", "hash", F.col("hub.node").alias("hub"), F.col("hub.grams").alias("hub_grams"))
    fits = F.least("grams", "hub_grams") >= F.lit(similarity) * F.greatest("grams", "hub_grams")
    stars = staged(buckets.join(hubs, ["band", "hash"]).where((F.col("node") != F.col("hub")) & fits).select(F.greatest("node", "hub").alias("a"), F.least("node", "hub").alias("b")).distinct(), "stars")
    links = staged(_near(stars, texts, n, similarity), "links")
    roots = staged(connected_components(links), "roots")
    # Buckets whose nodes fell into several components: look across components.
    placed = buckets.join(roots, "node", "left").select("band", "hash", "n", "node", F.coalesce("root", "node").alias("root"))
    split = placed.groupBy("band", "hash").agg(F.min("root").alias("r"), F.max("root").alias("s")).where("r <> s").select("band", "hash")
    tiles = F.ceil(F.col("n") / TILE).cast("int")
    mixed = staged(placed.join(split, ["band", "hash"]).withColumn("tile", F.pmod(F.xxhash64("node"), tiles).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), tiles - 1))), "mixed")
    groups = max(16, mixed.count() // GROUP_ROWS)
    tiled = mixed.withColumn("low", F.least("tile", "other")).withColumn("high", F.greatest("tile", "other")).withColumn("group", F.pmod(F.xxhash64("band", "hash", "low", "high"), F.lit(groups)))
    seen = tiled.join(nodes, "node").select("group", "band", "hash", "low", "high", "tile", "node", "root", "grams", "sketch", "hashes")
    more = seen.groupBy("group").applyInPandas(lambda part: _across(part, similarity), "a binary, b binary")
    more = staged(more.join(stars, ["a", "b"], "left_anti"), "more")
    added = staged(_near(more, texts, n, similarity), "links")
    if added.isEmpty():
        return links, roots
    links = staged(links.unionByName(added), "links")
    return links, staged(connected_components(links), "roots")


def _linked(sets: list[set], copies: np.ndarray, one: np.ndarray, two: np.ndarray, similarity: float) -> np.ndarray:
    """For each set, the copies of those it is linked to among the pairs of one x two; if both are the same
    rows, each is compared with all but itself."""
    ids: dict = {}
    flat = [np.fromiter((ids.setdefault(g, len(ids)) for g in s), np.int64, len(s)) for s in sets]
    size = np.array([len(f) for f in flat])
    row, gram = np.repeat(np.arange(len(sets)), size), np.concatenate(flat)
    # n-grams that many sets share are met by a matrix product, the others by lists of their holders.
    often = np.bincount(gram, minlength=len(ids)) * 16 >= max(len(sets), 64)
    column = np.cumsum(often) - 1
    dense = np.zeros((len(sets), int(often.sum())), np.float32)
    dense[row[often[gram]], column[gram[often[gram]]]] = 1
    row, gram = row[~often[gram]], gram[~often[gram]]
    begin = np.searchsorted(row, np.arange(len(sets) + 1))
    place = np.full(len(sets), -1)
    place[two] = np.arange(len(two))
    mine = place[row] >= 0
    order = np.argsort(gram[mine], kind="stable")
    holder, first = place[row[mine]][order], np.concatenate([[0], np.cumsum(np.bincount(gram[mine], minlength=len(ids)))])
    across, out, same = dense[two].T, np.zeros(len(sets)), np.array_equal(one, two)
    step = max(1, 2**18 // max(1, len(two)))
    for at in range(0, len(one), step):
        i = one[at : at + step]
        both = (dense[i] @ across).astype(np.int64)
        g = np.concatenate([gram[begin[x] : begin[x + 1]] for x in i])
        times = first[g + 1] - first[g]
        cell = np.repeat(np.repeat(np.arange(len(i)), begin[i + 1] - begin[i]) * len(two), times)
        cell += holder[np.arange(len(cell)) + np.repeat(first[g] - np.cumsum(times) + times, times)]
        both += np.bincount(cell, minlength=both.size).reshape(both.shape)
        like = both / (size[i][:, None] + size[two][None, :] - both) >= similarity
        if same:
            like &= i[:, None] != two[None, :]
        out[i] += like @ copies[two].astype(float)
        if not same:
            out[two] += copies[i].astype(float) @ like
    return out.astype(np.int64)


def linked_copies(placed: DataFrame, texts: DataFrame, n: int = N, similarity: float = SIMILARITY) -> DataFrame:
    """(node, linked): the documents of all other nodes whose full n-gram sets reach the similarity, over all pairs
    of each component. placed: (node, root, grams, copies) of the nodes that have a component.

    A component is cut into tiles of bounded size that meet in pairs, so that a large one is dealt to many tasks.
    """
    sizes = placed.groupBy("root").agg(F.ceil(F.greatest(F.count(F.lit(1)) / LINK_TILE, F.sum("grams") / LINK_GRAMS)).cast("int").alias("tiles"))
    tiled = placed.join(sizes, "root").withColumn("tile", F.pmod(F.xxhash64("node"), "tiles").cast("int")).join(_own_texts(placed.select("node"), texts), "node")
    met = tiled.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))).select("root", F.least("tile", "other").alias("low"), F.greatest("tile", "other").alias("high"), "tile", "node", "copies", "text")

    def run(batches):
        key, held = None, []

        def counted():
            tile, copies = np.array([r["tile"] for r in held]), np.array([r["copies"] for r in held], np.int64)
            one, two = np.flatnonzero(tile == key[1]), np.flatnonzero(tile == key[2])
            found = _linked([ngram_set(r["text"], n) for r in held], copies, one, two, similarity) if len(one) and len(two) else np.zeros(len(held), np.int64)
            return pa.RecordBatch.from_arrays([pa.array([r["node"] for r in held], pa.binary()), pa.array(found, pa.int64())], ["node", "linked"])

        for batch in batches:
            for r in batch.to_pylist():
                mine = r["root"], r["low"], r["high"]
                if mine != key:
                    if held:
                        yield counted()
                    key, held = mine, []
                held.append(r)
        if held:
            yield counted()

    parts = met.repartition("root", "low", "high").sortWithinPartitions("root", "low", "high").mapInArrow(run, "node binary, linked long")
    return parts.groupBy("node").agg(F.sum("linked").alias("linked"))


def near_duplicates(docs: DataFrame, n: int = N, similarity: float = SIMILARITY, recall: float = RECALL, most_hashes: int = MOST_HASHES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, class_id (least doc_id of its class), class_size, n_links and keep.

    n_links counts the other documents it is directly linked to: its copies, and all copies of the texts of its class
    that are similar to its own. keep marks one document of each class.
    """
    bands, rows = choose_bands(similarity, recall, most_hashes)
    signed = staged(signatures(docs, n, bands, rows, text_col, id_col).withColumn("row_no", F.monotonically_increasing_id()), "signatures")
    texts = _texts(docs, text_col)
    _, roots = similar_links(signed.where("grams > 0"), texts, n, similarity)
    nodes = signed.groupBy("node").agg(F.first("grams").alias("grams"), F.count(F.lit(1)).alias("copies"), F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "row_no")).alias("first"))
    nodes = staged(nodes.join(roots, "node", "left").select("node", "grams", "copies", "first", F.coalesce("root", "node").alias("root")), "nodes")
    linked = staged(linked_copies(nodes.join(roots.select("node"), "node").select("node", "root", "grams", "copies"), texts, n, similarity), "linked")
    classes = nodes.groupBy("root").agg(F.min("first").alias("head"), F.sum("copies").alias("class_size"))
    judged = nodes.join(classes, "root").join(linked, "node", "left").select("node", "head", "class_size", (F.coalesce("linked", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    return signed.join(judged, "node").select("doc_id", F.col("head.doc_id").alias("class_id"), "class_size", "n_links", (F.col("row_no") == F.col("head.row_no")).alias("keep"))


def drop_near_duplicates(docs: DataFrame, n: int = N, similarity: float = SIMILARITY, recall: float = RECALL) -> DataFrame:
    """docs with one row of each class; columns as they were. Rows of one doc_id with equal texts are copies."""
    bands, rows = choose_bands(similarity, recall)
    signed = staged(signatures(docs, n, bands, rows), "signatures")
    _, roots = similar_links(signed.where("grams > 0"), _texts(docs, "text"), n, similarity)
    nodes = signed.groupBy("node").agg(F.count(F.lit(1)).alias("copies"), F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id")).alias("first"))
    placed = nodes.join(roots, "node", "left").select("node", "copies", "first", F.coalesce("root", "node").alias("root"))
    heads = placed.groupBy("root").agg(F.min(F.struct("first", "node")).alias("head"), F.sum("copies").alias("size")).select(F.col("head.node").alias("node"), F.col("head.first.doc_id").alias("doc_id"), "size")
    key, head = fresh("near_node", docs.columns), fresh("near_doc", docs.columns)
    size = fresh("near_size", docs.columns)
    # Only the ids of the rows that go are joined with the texts.
    kept = heads.select(F.col("node").alias(key), F.col("doc_id").alias(head), F.col("size").alias(size))
    joined = docs.withColumn(key, F.unhex(F.md5(F.coalesce(F.col("text").cast("binary"), F.lit(b""))))).join(kept, key).where(F.col("doc_id").eqNullSafe(F.col(head)))
    single = joined.where(F.col(size) == 1).select(*columns_of(docs))
    several = joined.where(F.col(size) > 1).groupBy(key).agg(F.first(F.struct(*columns_of(docs))).alias("row")).select("row.*")
    return single.unionByName(several)


def op7_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
