"""Exact deduplication by two passes over a Bloom filter whose cells saturate at two.

Pass one hashes every row to two cells of one 64-bit word and keeps the cells that were hit
at least twice; pass two tests each row against those words. A row with a cell hit only once
has a unique hash, so it passes straight through; only possible repeats are shuffled.
False positives cost a little extra shuffling and never change the result.

Defined cases: a null text equals the empty text; equality is identity after lower-casing A-Z;
of equal texts the largest doc_id stays (a null doc_id counts as smallest; among rows of the same
doc_id one arbitrary row stays); an empty table gives an empty result; extra columns are kept.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, columns_of, fresh, join_by_weight, power_of_two, staged, table

#: The broadcast filter has at most this many bits (2**21 words), whatever the input: beyond about
#: 10 million rows more rows pass as possible repeats, and the exact stage still decides them.
MAX_FILTER_BITS = 2**27
CELLS_PER_ROW = 32


def text_digest(text: Column) -> Column:
    """SHA-256 (binary) of the normalised text."""
    return F.unhex(F.sha2(ascii_lower(F.coalesce(text, F.lit(""))), 256))


def _cells(digest: Column, words: int) -> tuple[Column, Column]:
    """Word number and two-bit mask of a row; both bits lie in the same word."""
    h = F.xxhash64(digest)
    first = F.shiftrightunsigned(h, 40).bitwiseAND(F.lit(63)).cast("int")
    second = (first + 1 + F.pmod(F.shiftrightunsigned(h, 48), F.lit(63)).cast("int")) % 64
    one = F.lit(1).cast("long")
    shift = lambda by: F.call_function("shiftleft", one, by)
    return F.pmod(h, F.lit(words)), shift(first).bitwiseOR(shift(second))


def repeat_filter(keys: DataFrame, digest: str = "digest", rows: int | None = None, max_bits: int = MAX_FILTER_BITS) -> tuple[DataFrame, int]:
    """Pass one: (word, bits) of the cells hit at least twice, and the number of words."""
    rows = keys.count() if rows is None else rows
    words = power_of_two(rows * CELLS_PER_ROW, 2**12, max_bits) // 64
    word, mask = _cells(F.col(digest), words)
    counted = keys.select(word.alias("word"), mask.alias("mask")).select("word", F.explode(F.array(F.col("mask").bitwiseAND(-F.col("mask")), F.col("mask").bitwiseAND(F.col("mask") - 1))).alias("bit")).groupBy("word", "bit").count().where("count >= 2")
    return counted.groupBy("word").agg(F.bit_or("bit").alias("bits")), words


def _marked(df: DataFrame, digest: str, filled: DataFrame, words: int, flag: str) -> DataFrame:
    """Pass two: add the flag of possible repeats. The filter has max_bits / 64 rows at most."""
    word, mask = _cells(F.col(digest), words)
    w, b = fresh("bloom_word", df.columns), fresh("bloom_bits", df.columns)
    slim = F.broadcast(filled.select(F.col("word").alias(w), F.col("bits").alias(b)))
    hit = F.coalesce(F.col(b).bitwiseAND(mask) == mask, F.lit(False))
    return df.join(slim, word == F.col(w), "left").withColumn(flag, hit).drop(w, b)


def exact_dedup_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", max_bits: int = MAX_FILTER_BITS) -> DataFrame:
    """One row per document, dropped ones too: doc_id, keep_id, group_size, kept, text_sha256."""
    keys = staged(docs.select(F.col(id_col).alias("doc_id"), text_digest(F.col(text_col)).alias("digest"), F.monotonically_increasing_id().alias("row_no")), "digests")
    rows = keys.count()
    filled, words = repeat_filter(keys, rows=rows, max_bits=max_bits)
    marked = _marked(keys, "digest", filled, words, "possible")
    some = marked.where("possible").drop("possible")
    groups = staged(some.groupBy("digest").agg(F.max(F.struct("doc_id", "row_no")).alias("top"), F.count(F.lit(1)).alias("group_size")), "groups")
    joined = join_by_weight(some, groups, ["digest"], "group_size", rows).select("doc_id", F.col("top.doc_id").alias("keep_id"), "group_size", (F.col("row_no") == F.col("top.row_no")).alias("kept"), "digest")
    alone = marked.where(~F.col("possible")).select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), "digest")
    return joined.unionByName(alone).withColumn("text_sha256", F.lower(F.hex("digest"))).drop("digest")


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", max_bits: int = MAX_FILTER_BITS) -> DataFrame:
    """The rows of docs that stay, all columns as they were. Rows with a unique hash never shuffle."""
    digest, flag, row = (fresh(x, docs.columns) for x in ("digest", "possible", "row"))
    keyed = docs.withColumn(digest, text_digest(F.col(text_col)))
    filled, words = repeat_filter(staged(keyed.select(F.col(digest).alias("digest")), "digests"), max_bits=max_bits)
    marked = _marked(keyed, digest, filled, words, flag)
    best = marked.where(F.col(flag)).groupBy(digest).agg(F.max_by(F.struct(*columns_of(docs)), F.struct(F.col(id_col), F.col(text_col))).alias(row))
    return marked.where(~F.col(flag)).select(*columns_of(docs)).unionByName(best.select(f"{row}.*"))


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup_report(table(spark, sf_dir, "documents"))


OP10_SQL = """
SELECT doc_id, max(doc_id) OVER same AS keep_id, count(*) OVER same AS group_size,
       doc_id = max(doc_id) OVER same AS kept, text_sha256
FROM (SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256
      FROM documents)
WINDOW same AS (PARTITION BY text_sha256)
"""
