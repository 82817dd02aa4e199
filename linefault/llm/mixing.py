"""Mixing sources to target weights by systematic sampling, in DataFrame operations alone.

Every document of a source is expected target / source_size times in the mix. The expected
copies are prefix-summed in order of size and of a hash of its id, one random offset per source is added, and a document
is emitted once for each integer boundary its interval crosses. Order by size makes the
sampled words of a source follow its target to about the largest document's size.

Prefix sums never pull a source into one task: documents are ranked inside
(source, size, slice), and only the counts of those groups are summed along a source. Slices are ranges of the hash, so
their number, which follows the number of rows, spreads a source or a single size with a third of all rows and leaves the
order, and what is drawn, as it is.

Defined cases: null text has size 0; null source is a source of its own, sorted last; a document
without words is taken 0 words (its copies are still whole numbers, given by the general operator);
rows of one doc_id are drawn one by one; an empty table gives an empty result; a null doc_id has hash 0.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import columns_of, fresh, power_of_two, staged, table

WORDS = r"[^\x20\x09-\x0D]+"
CYCLE = (1, 2, 3)
MOST = 3
SEED = 20240101
ROWS_PER_SLICE = 1_000_000
HASHES = 2**32


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORDS)), F.lit(0)).cast("long")


def unit_offset(source: Column, seed: int) -> Column:
    """A number in [0, 1) that depends on source and seed alone."""
    digest = F.md5(F.concat(F.coalesce(F.concat(F.lit("s:"), source), F.lit("null")), F.lit(f"/{seed}")))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def id_hash(doc_id: Column) -> Column:
    """32 bits of the id, the first key of the order inside a size."""
    return F.coalesce(F.conv(F.substring(F.md5(doc_id.cast("string").cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(0).cast("long"))


def source_targets(sized: DataFrame, weights: tuple = CYCLE, most: int = MOST) -> DataFrame:
    """(source, source_size, target): shares of all words by weight, stopped at `most` times the size.

    The table has one row per source, so its windows are over sources and not over rows. Sources
    fill up in order of capacity / weight; the first prefix whose common level no longer
    exceeds the next source's ratio is the solution.
    """
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    weighted = totals.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1).cast("int"))).withColumn("capacity", F.col("source_size") * F.lit(float(most)))
    every = Window.partitionBy()
    along = Window.orderBy((F.col("capacity") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = along.rowsBetween(Window.unboundedPreceding, -1)
    level = (F.sum("source_size").over(every) - F.coalesce(F.sum("capacity").over(before), F.lit(0.0))) / (F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    filled = weighted.withColumn("level", level).withColumn("open", F.col("level") * F.col("weight") <= F.col("capacity"))
    final = filled.withColumn("final", F.min(F.when(F.col("open"), F.struct(F.col("capacity") / F.col("weight"), F.col("level")))).over(every))
    return final.select("source", "source_size", F.coalesce(F.least("capacity", F.col("final.level") * F.col("weight")), F.col("capacity")).alias("target"))


def systematic_copies(sized: DataFrame, targets: DataFrame, seed: int = SEED, slices: int = 64) -> DataFrame:
    """Add source_size, target and copies to rows of (doc_id, source, size, ...). slices is a power of two."""
    ranked = sized.withColumn("hash", id_hash(F.col("doc_id"))).withColumn("slice", F.floor(F.col("hash") / F.lit(HASHES // slices)).cast("int"))
    key = ["source", "size", "slice"]
    # Two steps, so that the rows of a source's own window are its distinct sizes and nothing else.
    counts = ranked.groupBy(*key).agg(F.count(F.lit(1)).alias("n"))
    shorter = Window.partitionBy("source").orderBy("size").rowsBetween(Window.unboundedPreceding, -1)
    earlier = Window.partitionBy("source", "size").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    sizes = counts.groupBy("source", "size").agg(F.sum("n").alias("n")).select(F.col("source").alias("z_source"), F.col("size").alias("z_size"), F.coalesce(F.sum("n").over(shorter), F.lit(0)).alias("below"))
    inside = counts.withColumn("ahead", F.coalesce(F.sum("n").over(earlier), F.lit(0)))
    starts = inside.join(sizes, F.col("source").eqNullSafe(F.col("z_source")) & (F.col("size") == F.col("z_size"))).select(*key, (F.col("below") + F.col("ahead")).alias("start"))
    inner = Window.partitionBy(*key).orderBy("hash", "doc_id")
    right = targets.select(F.col("source").alias("t_source"), "source_size", "target")
    placed = starts.join(F.broadcast(right), F.col("source").eqNullSafe(F.col("t_source"))).select(F.col("source").alias("s_source"), F.col("size").alias("s_size"), F.col("slice").alias("s_slice"), "start", "source_size", "target")
    at = ranked.withColumn("place", F.row_number().over(inner))
    same = F.col("source").eqNullSafe(F.col("s_source")) & (F.col("size") == F.col("s_size")) & (F.col("slice") == F.col("s_slice"))
    rate = F.coalesce(F.try_divide(F.col("target"), F.col("source_size")), F.lit(0.0))
    edge = lambda k: F.floor(k * F.col("rate") + F.col("offset"))
    upto = F.col("start") + F.col("place")
    return at.join(placed, same).withColumn("rate", rate).withColumn("offset", unit_offset(F.col("source"), seed)).withColumn("copies", (edge(upto) - edge(upto - 1)).cast("long")).drop("s_source", "s_size", "s_slice", "slice", "hash", "start", "place", "rate", "offset")


def _sized(docs: DataFrame, id_col: str, text_col: str, source_col: str) -> tuple[DataFrame, int]:
    sized = staged(docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), word_count(F.col(text_col)).alias("size")), "sizes")
    return sized, power_of_two(sized.count() / ROWS_PER_SLICE, 64, HASHES)


def mix_report(docs: DataFrame, weights: tuple = CYCLE, most: int = MOST, seed: int = SEED) -> DataFrame:
    """One row per document: doc_id, size, source_size, target (to a millionth of a word), taken."""
    sized, slices = _sized(docs, "doc_id", "text", "source")
    taken = systematic_copies(sized, source_targets(sized, weights, most), seed, slices)
    return taken.select("doc_id", "size", "source_size", F.round("target", 6).alias("target"), (F.col("copies") * F.col("size")).alias("taken"))


def mix_sources(docs: DataFrame, weights: tuple = CYCLE, most: int = MOST, seed: int = SEED) -> DataFrame:
    """The mix itself: the rows of docs, each as often as it is taken; columns as they were.

    Documents without words are weightless: they follow their source's rate like the others. Rows that agree in doc_id,
    source and size share what these are drawn: as evenly as whole copies allow, and never more than is reported.
    """
    sized, slices = _sized(docs, "doc_id", "text", "source")
    drawn = systematic_copies(sized, source_targets(sized, weights, most), seed, slices)
    key, of, words, times, rows, each, place = (fresh(x, docs.columns) for x in ("mix_id", "mix_source", "mix_size", "mix_times", "mix_rows", "mix_each", "mix_place"))
    slim = drawn.groupBy("doc_id", "source", "size").agg(F.sum("copies").alias(times), F.count(F.lit(1)).alias(rows)).where(F.col(times) > 0).select(F.col("doc_id").alias(key), F.col("source").alias(of), F.col("size").alias(words), times, rows)
    same = F.col("doc_id").eqNullSafe(F.col(key)) & F.col("source").eqNullSafe(F.col(of)) & (word_count(F.col("text")) == F.col(words))
    joined = docs.join(slim, same)
    single = joined.where(F.col(rows) == 1).withColumn(place, F.lit(1))
    # Only rows that share an id, a source and a size are numbered, and so shuffled once more.
    numbered = Window.partitionBy(key, of, words).orderBy(F.monotonically_increasing_id())
    several = joined.where(F.col(rows) > 1).withColumn(place, F.row_number().over(numbered))
    share = F.floor(F.col(times) / F.col(rows)) + F.when(F.col(place) <= F.pmod(times, rows), 1).otherwise(0)
    return single.unionByName(several).withColumn(each, F.explode(F.array_repeat(F.lit(1), share.cast("int")))).select(*columns_of(docs))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_report(table(spark, sf_dir, "documents"))


OP8_SQL = f"""
WITH sized AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size FROM documents),
totals AS (SELECT source, sum(size)::BIGINT AS source_size, count(*) AS n FROM sized GROUP BY source),
w AS (SELECT *, 1.0 + (row_number() OVER (ORDER BY encode(source) NULLS LAST) - 1) % 3 AS weight, 3.0 * source_size AS capacity FROM totals),
lev AS (
  SELECT a.*, ((SELECT sum(source_size) FROM w) - coalesce((SELECT sum(b.capacity) FROM w b WHERE b.capacity / b.weight < a.capacity / a.weight), 0))
            / (SELECT sum(b.weight) FROM w b WHERE b.capacity / b.weight >= a.capacity / a.weight) AS level
  FROM w a),
common AS (SELECT arg_min(level, capacity / weight) AS l FROM lev WHERE level * weight <= capacity),
target AS (SELECT source, source_size, least(capacity, l * weight)::DOUBLE AS target FROM w, common),
placed AS (
  SELECT s.doc_id, s.size, t.source_size, t.target,
         row_number() OVER (PARTITION BY s.source ORDER BY s.size, ('0x' || substr(md5(s.doc_id::VARCHAR), 1, 8))::BIGINT, s.doc_id) AS k,
         ('0x' || substr(md5(coalesce('s:' || s.source, 'null') || '/{SEED}'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u,
         CASE WHEN t.source_size = 0 THEN 0 ELSE t.target / t.source_size END AS c
  FROM sized s JOIN target t ON s.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, round(target, 6) AS target, (size * (floor(k * c + u) - floor((k - 1) * c + u)))::BIGINT AS taken FROM placed
"""
