import collections

import duckdb
import pytest

import corpus_pipeline
from linefault.llm import exact_dedup, mixing, ngram_join, packing, quality
from linefault.llm.queries import ORACLE_SQL, QUERIES

from .test_rows import lowered, near_brute, same_partition  # noqa: F401


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_query_equals_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got, want = QUERIES[name](spark, sf).toPandas(), con.execute(ORACLE_SQL[name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)

    def rows(df):
        return sorted(tuple("" if v is None or v != v else f"{v:.6f}" if isinstance(v, float) else str(v) for v in r) for r in df[cols].itertuples(index=False))

    assert rows(got) == rows(want)


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = corpus_pipeline.staged(stage(spark, docs, sf), name)
        assert out.columns == columns
        seen[name] = (docs.collect(), out.collect())
        docs = out
    before, after = seen["quality"]
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    kept = {r.doc_id for r in after}
    assert sum(i in kept for i, q in labels.items() if q == 1) > 0.9 * sum(labels.values())
    before, after = seen["exact_dedup"]
    groups = collections.defaultdict(list)
    for r in before:
        groups[lowered(r.text)].append(r.doc_id)
    assert {r.doc_id for r in after} == {max(g) for g in groups.values()}
    before, after = seen["near_dedup"]
    classes = near_brute([(r.doc_id, r.text) for r in before])
    of = {r.doc_id: c for r, c in zip(before, classes, strict=True)}
    assert sorted({of[r.doc_id] for r in after}) == sorted(set(classes)) and len(after) == len(set(classes))
    before, after = seen["mixing"]
    times = collections.Counter(r.doc_id for r in after)
    assert max(times.values()) <= 3
    pieces = packing.pack(docs).collect()
    assert sum(r.start == 0 for r in pieces) == len(after)


def odd_folder(spark, folder, rows):
    """A folder with documents of odd rows and with labels of some of them."""
    form = "doc_id long, text string, lang string, source string, n_chars long, stats string, near_size int"
    spark.createDataFrame([(i, t, None, s, None, "kept", k) for k, (i, t, s) in enumerate(rows)], form).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(i, None if i == 4 else 1, 0) for i, _, _ in rows], "doc_id long, quality long, toxic long").write.parquet(f"{folder}/labels.parquet")
    return str(folder)


def test_stages_on_odd_rows(spark, odd, tmp_path):
    """Nulls, empty and long texts, ties, repeated rows, and columns named like the operators' own."""
    folder = odd_folder(spark, tmp_path / "odd", [*odd, (8, "é😀 TIE", None), (9, "word " * 30_000, "b"), (10, "a b c d e f g", "c"), (11, "a b c d e  f g", "c")])
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    columns, whole = docs.columns, {(r.doc_id, r.text): r.near_size for r in docs.collect()}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = docs.count()
        out = corpus_pipeline.staged(stage(spark, docs, folder), name)
        rows = out.collect()
        assert out.columns == columns and all(r.stats == "kept" and (r.doc_id, r.text) in whole for r in rows)
        if name == "quality":
            assert len(rows) == before
        if name == "exact_dedup":
            texts = [lowered(r.text) for r in rows]
            assert len(texts) == len(set(texts)) and {r.doc_id for r in rows if r.text == "word " * 30_000} == {9}
        if name == "near_dedup":
            assert {r.doc_id for r in rows} & {10, 11} == {10}
        docs = out
    pieces = packing.pack(docs).collect()
    assert sum(r.start == 0 for r in pieces) == docs.count()


def test_run_on_an_empty_table(spark, tmp_path):
    folder = odd_folder(spark, tmp_path / "none", [])
    assert corpus_pipeline.run(spark, folder).count() == 0


def test_run_on_one_row(spark, tmp_path):
    folder = odd_folder(spark, tmp_path / "one", [(7, "only one", "a")])
    assert [(r.doc_id, r.start, r.sequence_id, r.offset) for r in corpus_pipeline.run(spark, folder).collect()] == [(7, 0, 0, 0)]


def test_run(spark, sf):
    assert corpus_pipeline.run(spark, sf).columns == ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]


def test_stage_modules_are_the_operators():
    assert [quality.__name__, exact_dedup.__name__, ngram_join.__name__, mixing.__name__, packing.__name__] == [f"linefault.llm.{x}" for x in ("quality", "exact_dedup", "ngram_join", "mixing", "packing")]
