"""URL filtering: a blocked Bloom filter of listed canonical URLs, then an exact hash join.

A list entry is a host and the beginning of a path; it fits its host, all subdomains and every path
that starts so. Each URL asks for the few (host suffix, path beginning) keys whose label count and
length occur in the list. The Bloom filter answers first: rows without a possible hit pass straight
through, the others are exploded to their possible keys and joined with the list by hash, which
removes the false positives. The longest rule wins (equal lengths: the longer host, then by name);
without a rule the block list decides, and without either the URL is allowed. Rules ask for host and path as they stand;
the block list holds canonical URLs and asks for the canonical host, without user, port and final dots, and for the path `/`
where there is none.

Defined cases: null URLs and those without `://` have empty host and path, fit nothing and are
allowed; null list entries fit nothing; repeated list entries count once; an empty list allows all; extra
columns are kept.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ascii_lower, fresh, power_of_two, table

#: Rules as (host, path, verdict).
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
#: The default block list, canonical URLs of host and path beginning.
LISTED = ("adult-x.example.net/", "ads-track.example.com/", "casino-win.example.com/", "cheap-pills.example.com/", "free-bets.example.com/", "spam-farm.example.com/", "spam-farm.example.org/")

BLOCK_WORDS = 8
#: 2**16 blocks of 512 bits: the filter is 4 MB at most, whatever the list; beyond 2 million entries
#: more false positives reach the exact join.
MAX_BLOCKS = 2**16
ENTRY_BITS = 16


def host_and_path(url: Column) -> tuple[Column, Column]:
    rest = F.when(F.contains(url, F.lit("://")), F.substr(url, F.length(F.substring_index(url, "://", 1)) + 4))
    raw = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substr(rest, F.length(raw) + 1), r"^[^?#]*", 0)
    return F.coalesce(ascii_lower(raw), F.lit("")), F.coalesce(path, F.lit(""))


def canonical(host: Column, path: Column) -> tuple[Column, Column]:
    """Host without user part, port and final dots; path that begins with a slash."""
    bare = F.regexp_replace(F.regexp_replace(F.regexp_replace(host, "^.*@", ""), ":[0-9]*$", ""), r"\.+$", "")
    return bare, F.when(path == "", F.lit("/")).otherwise(path)


def _asked(kind: str, host: Column, path: Column, shapes: list[tuple[int, int]]) -> Column:
    """The keys that a URL can have in a list: one for each pair of label count and path length that the list has. The pairs
    are one array literal, so the plan does not grow with them."""
    labels = F.split(host, r"\.")
    pairs = F.array(*[F.struct(F.lit(a).alias("labels"), F.lit(b).alias("chars")) for a, b in shapes]) if shapes else F.array().cast("array<struct<labels:int,chars:int>>")
    fits = F.filter(pairs, lambda x: (F.size(labels) >= x["labels"]) & (F.length(path) >= x["chars"]) & (host != ""))
    ending = lambda x: F.array_join(F.slice(labels, F.size(labels) - x["labels"] + 1, x["labels"]), ".")
    return F.transform(fits, lambda x: F.concat_ws("\n", F.lit(kind), ending(x), F.substr(path, F.lit(1), x["chars"])))


def _slots(hashes: np.ndarray, blocks: int) -> tuple[np.ndarray, np.ndarray]:
    """Block of each hash, and its eight masks, one bit in each word of the block."""
    h = hashes.astype(np.uint64)
    block = (h >> np.uint64(32)) & np.uint64(blocks - 1)
    salts = (np.arange(BLOCK_WORDS, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
    bits = (((h & np.uint64(0xFFFFFFFF)) + np.uint64(1))[:, None] * salts[None, :]) >> np.uint64(58)
    return block.astype(np.int64), np.uint64(1) << bits


def bloom_blocks(entries: DataFrame) -> np.ndarray:
    """The blocked filter over column `key`: each task ORs its own blocks, Spark ORs the words.

    What reaches the driver is (block, word, bits), MAX_BLOCKS * 8 rows at most.
    """
    hashed = entries.select(F.xxhash64("key").alias("h")).distinct()
    blocks = power_of_two(hashed.count() * ENTRY_BITS / 512, 16, MAX_BLOCKS)

    def words(batches):
        for batch in batches:
            block, masks = _slots(batch["h"].to_numpy(), blocks)
            own = np.zeros((blocks, BLOCK_WORDS), np.uint64)
            np.bitwise_or.at(own, block, masks)
            at = np.flatnonzero(own.ravel())
            yield pd.DataFrame({"word": at, "bits": own.ravel()[at].astype(np.int64)})

    out = np.zeros(blocks * BLOCK_WORDS, np.uint64)
    for row in hashed.mapInPandas(words, "word long, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toLocalIterator():
        out[row.word] = np.uint64(row.bits & 0xFFFFFFFFFFFFFFFF)
    return out.reshape(blocks, BLOCK_WORDS)


def may_contain(blocks: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    block, masks = _slots(hashes, len(blocks))
    return ((blocks[block] & masks) == masks).all(axis=1)


def filter_urls(pages: DataFrame, rules: DataFrame, listed: DataFrame, url_col: str = "url") -> DataFrame:
    """pages with host, path, rule and verdict (with an underscore before each name that pages has already).

    rules has (host, path, verdict); listed has (url), canonical and without scheme, as `host/path`.
    """
    lists = listed.select(F.regexp_extract("url", r"^[^/]*", 0).alias("host"), F.regexp_extract("url", r"/.*$", 0).alias("path"), F.lit("block").alias("verdict"), F.lit(0).alias("is_rule"))
    entries = rules.select("host", "path", "verdict", F.lit(1).alias("is_rule")).unionByName(lists).where("host is not null and path is not null").withColumn("key", F.concat_ws("\n", F.when(F.col("is_rule") == 1, "rule").otherwise("list"), ascii_lower(F.col("host")), "path"))
    shapes = entries.select("is_rule", F.size(F.split("host", r"\.")).alias("labels"), F.length("path").alias("chars")).distinct().collect()  # label counts and path lengths, not entries
    of = {kind: sorted((r.labels, r.chars) for r in shapes if r.is_rule == kind) for kind in (0, 1)}
    blocks = pages.sparkSession.sparkContext.broadcast(bloom_blocks(entries))

    host, path, keys, possible, row, key, rule, verdict, bare, full = (fresh(x, pages.columns) for x in ("host", "path", "url_keys", "url_possible", "url_row", "url_key", "rule", "verdict", "url_host", "url_path"))
    h, p = host_and_path(F.col(url_col))

    @F.pandas_udf(T.ArrayType(T.BooleanType()))
    def hits(hashes: pd.Series) -> pd.Series:
        sizes = hashes.map(len).to_numpy()
        flat = np.concatenate(hashes.to_list()) if sizes.sum() else np.zeros(0, np.int64)
        return pd.Series(np.split(may_contain(blocks.value, flat), np.cumsum(sizes)[:-1]) if len(sizes) else [], dtype=object)

    named = pages.withColumns({host: h, path: p})
    named = named.withColumns(dict(zip((bare, full), canonical(F.col(host), F.col(path)), strict=True)))
    named = named.withColumn(keys, F.concat(_asked("rule", F.col(host), F.col(path), of[1]), _asked("list", F.col(bare), F.col(full), of[0]))).drop(bare, full)
    tested = named.withColumn(possible, hits(F.transform(F.col(keys), lambda x: F.xxhash64(x))))
    some = F.filter(F.transform(F.arrays_zip(keys, possible), lambda x: F.when(x[possible], x[keys])), lambda x: x.isNotNull())
    tested = tested.withColumn(keys, some).drop(possible)
    own = [F.col(f"`{c}`") for c in [*pages.columns, host, path]]

    asked_rows = tested.where(F.size(keys) > 0).withColumn(row, F.monotonically_increasing_id()).select(F.struct(*own).alias("page"), row, F.explode(keys).alias(key))
    exact = entries.groupBy("key", "is_rule").agg(F.max_by(F.struct("host", "path", "verdict"), F.col("verdict")).alias("entry"))
    rank = F.struct("is_rule", F.length(F.concat("entry.host", "entry.path")).alias("n"), F.length("entry.host").alias("m"), F.concat("entry.host", "entry.path").alias("rule"), F.col("entry.verdict").alias("verdict"))
    found = asked_rows.join(exact, asked_rows[key] == exact["key"], "left").groupBy(row).agg(F.first("page").alias("page"), F.max(F.when(F.col("entry").isNotNull(), rank)).alias("top"))
    judged = found.select("page.*", F.when(F.col("top.is_rule") == 1, F.col("top.rule")).alias(rule), F.coalesce("top.verdict", F.lit("allow")).alias(verdict))
    passed = tested.where(F.size(keys) == 0).select(*own, F.lit(None).cast("string").alias(rule), F.lit("allow").alias(verdict))
    return judged.unionByName(passed)


def default_lists(spark: SparkSession) -> tuple[DataFrame, DataFrame]:
    return spark.createDataFrame(list(RULES), "host string, path string, verdict string"), spark.createDataFrame([(x,) for x in LISTED], "url string")


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules, listed = default_lists(spark)
    return filter_urls(table(spark, sf_dir, "pages").select("page_id", "url"), rules, listed).select("page_id", "host", "path", "rule", "verdict")


OP4_SQL = f"""
WITH cut AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
named AS (
  SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(substr(rest, length(regexp_extract(rest, '^[^/?#]*')) + 1), '^[^?#]*') AS path FROM cut),
rules(h, p, v) AS (VALUES {', '.join(str(r) for r in RULES)}),
listed(h) AS (VALUES {', '.join(f"('{x[:-1]}')" for x in LISTED)}),
ruled AS (
  SELECT page_id, host, path, (SELECT arg_max([h || p, v], length(h || p)) FROM rules
         WHERE (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p)) AS best,
         EXISTS (SELECT 1 FROM listed WHERE (bare = h OR ends_with(bare, '.' || h)) AND (path = '' OR starts_with(path, '/'))) AS bad
  FROM (SELECT *, regexp_replace(regexp_replace(regexp_replace(host, '^.*@', ''), ':[0-9]*$', ''), '\\.+$', '') AS bare FROM named))
SELECT page_id, host, path, best[1] AS rule, coalesce(best[2], CASE WHEN bad THEN 'block' ELSE 'allow' END) AS verdict FROM ruled
"""
