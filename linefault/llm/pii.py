"""Personal data: base patterns, and information-theoretic sanitisation of terms that reveal them.

Base spans are the matches of four patterns. The protected entities are their values. Over the
corpus, a term is compared with each entity it shares lines with: the pointwise mutual information
PMI = log2(N n(term, entity) / (n(term) n(entity))) says how many bits of the entity's own information
IC = log2(N / n(entity)) the term gives away. A term with enough joint support whose PMI reaches
DISCLOSURE of IC is a disclosure and is marked (and removed or generalised) like the entity itself.
All counts are over distinct lines of the whole corpus, so copies of a document add no evidence.

Everything is DataFrame functions. No pattern crosses a line break or backtracks over long runs: the
published expressions are rewritten with possessive repeats and tests of the character before, which
match the same spans.

Defined cases: null text counts as empty; offsets count code points; equal texts get equal spans;
null or repeated doc_id each give their own row; an empty table gives an empty result.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import columns_of, fresh, join_by_weight, staged, table

#: Fixed order of the kinds.
KINDS = ("email", "ip", "card", "phone")
LOCAL = "A-Za-z0-9._%+-"
#: A pattern's match may also start where the last match ended, which \G says.
PATTERNS = {
    "email": rf"(?:(?<![{LOCAL}])|\G)[{LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}+",
    "card": r"(?<![0-9])(?<![0-9][ -])[0-9](?:[ -]?[0-9]){13,18}+(?![ -]?[0-9])",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
#: Cheap tests that every match needs.
HINTS = {"email": "@", "ip": r"[0-9]\.[0-9]++\.[0-9]", "card": r"[0-9](?:[ -]?[0-9]){13}", "phone": r"\+[0-9]"}
OCTET = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
#: Terms are runs of letters this long at least.
TERM = r"\p{L}{4,}+"
SUPPORT = 5
DISCLOSURE = 0.95
TERM_KIND = "term"
#: Bits of the filter that keeps the corpus count to possible terms; fixed, so the broadcast is bounded (2**18 words, and
#: no more than there are terms); more candidate terms only let more words through to the exact join.
TERM_FILTER_BITS = 2**24
#: The lines of one in so many hash classes are counted in turn. What a part holds is a lower bound of a term's count and
#: so rules terms out exactly; only the terms left are counted over the next part, and in the end over all lines.
PARTS = (16, 1)


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    n = F.length(digits)

    def add(total, i):
        d = F.substr(digits, i, F.lit(1)).cast("int")
        twice = F.when(d > 4, d * 2 - 9).otherwise(d * 2)
        return total + F.when((n - i) % 2 == 1, twice).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), n), F.lit(0), add) % 10 == 0


def _valid(kind: str, x: Column) -> Column:
    if kind == "ip":
        return x.rlike(rf"^{OCTET}(?:\.{OCTET}){{3}}$")
    if kind == "card":
        return F.length(_digits(x)).between(14, 19) & _luhn(_digits(x))
    if kind == "phone":
        return F.length(_digits(x)).between(10, 15)
    return F.lit(True)


def _located(text: Column, pattern: str) -> Column:
    """Array of (start, end, value) of all matches: each find takes the gap before it, anchored at the last end."""
    whole = rf"\G([\s\S]*?)({pattern})"
    pairs = F.arrays_zip(F.regexp_extract_all(text, F.lit(whole), 1).alias("gap"), F.regexp_extract_all(text, F.lit(whole), 2).alias("value"))
    start = F.struct(F.lit(0).alias("end"), F.lit(None).cast("array<struct<start:int,end:int,value:string>>").alias("all"))

    def step(acc, x):
        begin = acc["end"] + F.length(x["gap"])
        end = begin + F.length(x["value"])
        here = F.array(F.struct(begin.alias("start"), end.alias("end"), x["value"].alias("value")))
        return F.struct(end.alias("end"), F.when(acc["all"].isNull(), here).otherwise(F.concat(acc["all"], here)).alias("all"))

    return F.aggregate(pairs, start, step, lambda acc: F.coalesce(acc["all"], F.array().cast("array<struct<start:int,end:int,value:string>>")))


def base_spans(text: Column, kind: str) -> Column:
    """Valid matches of one kind, as array of (start, end, value); texts without the hint skip the search."""
    hint = F.contains(text, F.lit("@")) if kind == "email" else text.rlike(HINTS[kind])
    empty = F.array().cast("array<struct<start:int,end:int,value:string>>")
    return F.when(hint, F.filter(_located(text, PATTERNS[kind]), lambda x: _valid(kind, x["value"]))).otherwise(empty)


def _text(docs: DataFrame, text_col: str) -> Column:
    return F.coalesce(F.col(text_col), F.lit(""))


def _listed(spans: Column) -> Column:
    """kind:start:end by start, then kind as listed, comma-joined."""
    return F.array_join(F.transform(F.array_sort(spans), lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def _as_spans(spans: Column, kind: str, rank: int) -> Column:
    return F.transform(spans, lambda x: F.struct(x["start"].alias("start"), F.lit(rank).alias("rank"), x["end"].alias("end"), F.lit(kind).alias("kind")))


def _text_key(text: Column) -> Column:
    return F.sha2(text, 256)


def disclosing_terms(docs: DataFrame, text_col: str = "text", support: int = SUPPORT, disclosure: float = DISCLOSURE) -> DataFrame:
    """The terms that give away a protected entity: (term, entity, n_joint, n_term, n_entity, pmi, ic)."""
    texts = docs.select(_text(docs, text_col).alias("text"))
    any_hint = reduce(lambda a, b: a | b, [F.contains("text", F.lit("@")), *[F.col("text").rlike(HINTS[k]) for k in KINDS[1:]]])
    lines = texts.select(F.explode(F.split("text", "\n")).alias("text")).where(F.col("text") != "")
    named = lambda kind: F.transform(base_spans(F.col("text"), kind), lambda x: F.concat(F.lit(f"{kind}:"), x["value"]))
    marked = lines.where(any_hint).withColumn("entities", F.array_distinct(F.flatten(F.array(*[named(k) for k in KINDS]))))
    words = lambda text: F.array_distinct(F.transform(F.regexp_extract_all(text, F.lit(TERM), F.lit(0)), F.lower))
    terms, bare = words(F.col("text")), F.col("text")
    for k in KINDS:  # an entity's own letters are no evidence
        bare = F.regexp_replace(bare, PATTERNS[k], " ")
    context = staged(marked.where(F.size("entities") > 0).select(F.xxhash64("text").alias("line"), "entities", words(bare).alias("terms")), "contexts").dropDuplicates(["line"])
    # Entities seen in fewer lines than the support can have no supported term.
    entity_lines = context.select("line", "terms", F.explode("entities").alias("entity"))
    entities = entity_lines.groupBy("entity").agg(F.count(F.lit(1)).alias("n_entity")).where(F.col("n_entity") >= support)
    joint = entity_lines.join(entities, "entity").select("entity", "n_entity", F.explode("terms").alias("term")).groupBy("entity", "term").agg(F.count(F.lit(1)).alias("n_joint"), F.max("n_entity").alias("n_entity")).where(F.col("n_joint") >= support)
    total = lines.select(F.xxhash64("text").alias("line")).distinct().count()
    bits = lambda n_term: F.log2(F.lit(float(max(total, 1))) * F.col("n_joint") / (F.col(n_term) * F.col("n_entity")))
    own = F.log2(F.lit(float(max(total, 1))) / F.col("n_entity"))
    # A term stands in at least as many lines as in lines with entities, so most terms are ruled out, exactly,
    # before the corpus is counted.
    least = context.select("line", F.explode("terms").alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("n_least"))
    joint = staged(joint.join(least, "term").where((own > 0) & (bits("n_least") >= disclosure * own)).drop("n_least"), "joint")
    spoken = lines.select(F.xxhash64("text").alias("line"), F.explode(terms).alias("term"))

    def heard_in(rows: DataFrame, wanted: DataFrame) -> DataFrame:
        """(term, n_term): in how many distinct lines of `rows` each wanted term stands."""
        bloom, words = _term_filter(wanted)
        possible = _possible_terms(rows, bloom, words)
        return possible.distinct().groupBy("term").agg(F.count(F.lit(1)).alias("n_term"))

    for part in PARTS:
        rows = spoken.where(F.pmod("line", F.lit(part)) == 0)
        wanted = joint.select("term").distinct()
        if wanted.isEmpty():
            return joint.select("term", "entity", "n_joint", F.lit(0).cast("long").alias("n_term"), "n_entity", F.lit(0.0).alias("pmi"), F.lit(0.0).alias("ic"))
        heard = heard_in(rows, wanted)
        if part > 1:
            least = joint.join(heard, "term", "left").withColumn("n_term", F.greatest(F.coalesce("n_term", F.lit(0)), "n_joint"))
            joint = staged(least.where(bits("n_term") >= disclosure * own).select("entity", "term", "n_joint", "n_entity"), "joint")
    scored = joint.join(heard, "term").withColumn("pmi", bits("n_term")).withColumn("ic", own)
    return scored.where(F.col("pmi") >= disclosure * F.col("ic"))


def find_personal_data(docs: DataFrame, support: int = SUPPORT, disclosure: float = DISCLOSURE) -> DataFrame:
    """doc_id, counts by kind, base_sha256, spans (text), and all_spans (array of start, rank, end, kind)."""
    text = _text(docs, "text")
    named = docs.select("doc_id", text.alias("text"))
    found = named.select("doc_id", _text_key(F.col("text")).alias("key"), *[base_spans(F.col("text"), k).alias(k) for k in KINDS])
    base = F.concat(*[_as_spans(F.col(k), k, i) for i, k in enumerate(KINDS)])
    counted = staged(found.select("doc_id", "key", *[F.size(k).cast("long").alias(f"n_{k}") for k in KINDS], base.alias("base")), "base")
    terms = staged(disclosing_terms(docs, "text", support, disclosure).select("term").distinct(), "terms")
    extra = term_spans(named.select(_text_key(F.col("text")).alias("key"), "text"), terms)
    none = F.array().cast("array<struct<start:int,rank:int,end:int,kind:string>>")
    # A text with terms may stand in a third of all rows: such texts are met by broadcast, and there are few of them.
    total = counted.count()
    weighed = staged(extra.join(counted.groupBy("key").agg(F.count(F.lit(1)).alias("weight")), "key"), "weighed")
    met = join_by_weight(counted, weighed, ["key"], "weight", total).drop("weight")
    rest = counted.join(weighed.select("key"), "key", "left_anti").withColumn("extra", none)
    joined = met.unionByName(rest).withColumn("all_spans", F.concat("base", "extra"))
    return joined.select("doc_id", *[f"n_{k}" for k in KINDS], F.sha2(_listed(F.col("base")), 256).alias("base_sha256"), _listed(F.col("all_spans")).alias("spans"), "all_spans")


def _place(name: str, words: int) -> tuple[Column, Column]:
    """Word and bit of a value in a filter."""
    h = F.xxhash64(name)
    return F.pmod(h, F.lit(words)), F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(h, 58).cast("int"))


def _key_filter(rows: DataFrame, name: str = "key") -> tuple[DataFrame, int]:
    """(word, bits) of a filter of fixed size over a column, and its number of words."""
    words = TERM_FILTER_BITS // 64
    word, bit = _place(name, words)
    return rows.select(word.alias("word"), bit.alias("bit")).groupBy("word").agg(F.bit_or("bit").alias("bits")), words


def _term_filter(terms: DataFrame) -> tuple[DataFrame, int]:
    return _key_filter(terms, "term")


def _possible_terms(spoken: DataFrame, bloom: DataFrame, words: int) -> DataFrame:
    """Rows whose term the filter may hold; decided where the rows are, before any shuffle."""
    word, bit = _place("term", words)
    return spoken.join(F.broadcast(bloom), word == F.col("word")).where(F.col("bits").bitwiseAND(bit) != 0).drop("word", "bits")


def term_spans(texts: DataFrame, terms: DataFrame) -> DataFrame:
    """(key, extra): where the disclosing terms stand, once per distinct text that holds any."""
    spoken = texts.select("key", F.explode(F.array_distinct(F.transform(F.regexp_extract_all("text", F.lit(TERM), F.lit(0)), F.lower))).alias("term"))
    bloom, words = _term_filter(terms)
    held = staged(_possible_terms(spoken, bloom, words).join(terms, "term", "left_semi").groupBy("key").agg(F.collect_set("term").alias("terms")), "held")
    if held.isEmpty():
        return held.select("key", F.array().cast("array<struct<start:int,rank:int,end:int,kind:string>>").alias("extra"))
    # Texts without a term stay where they are; the copies of the others become one map-side before they meet their terms.
    bloom, words = _key_filter(held)
    word, bit = _place("key", words)
    some = texts.join(F.broadcast(bloom), word == F.col("word")).where(F.col("bits").bitwiseAND(bit) != 0).select("key", "text")
    placed = some.groupBy("key").agg(F.first("text").alias("text")).join(held, "key")
    own = F.filter(_located(F.col("text"), TERM), lambda x: F.array_contains("terms", F.lower(x["value"])))
    return placed.select("key", _as_spans(own, TERM_KIND, len(KINDS)).alias("extra"))


def sanitise(docs: DataFrame, support: int = SUPPORT, disclosure: float = DISCLOSURE) -> DataFrame:
    """docs with each span of text generalised to [KIND]; overlapping spans become one mask of the first kind.

    Rows are matched by text, so doc_id may repeat or be null.
    """
    spans = find_personal_data(docs.select(F.sha2(_text(docs, "text"), 256).alias("doc_id"), "text").dropDuplicates(["doc_id"]), support, disclosure)
    key, found = fresh("sanitise_key", docs.columns), fresh("sanitise_spans", docs.columns)
    joined = docs.withColumn(key, F.sha2(_text(docs, "text"), 256)).join(spans.where(F.size("all_spans") > 0).select(F.col("doc_id").alias(key), F.array_sort("all_spans").alias(found)), key, "left")

    def step(acc, x):
        masked = F.concat(acc["out"], F.substr(F.col("text"), acc["at"] + 1, x["start"] - acc["at"]), F.lit("["), F.upper(x["kind"]), F.lit("]"))
        return F.when(x["start"] >= acc["at"], F.struct(x["end"].alias("at"), masked.alias("out"))).otherwise(F.struct(F.greatest(acc["at"], x["end"]).alias("at"), acc["out"].alias("out")))

    clean = F.aggregate(F.col(found), F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step, lambda acc: F.concat(acc["out"], F.substr(F.col("text"), acc["at"] + 1, F.length("text"))))
    return joined.withColumn("text", F.when(F.col(found).isNull(), F.col("text")).otherwise(clean)).select(*columns_of(docs))


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_personal_data(table(spark, sf_dir, "documents")).drop("all_spans")
