"""The corpus pipeline: five stages, each one of the training-data operators.

Every stage takes (spark, docs, sf_dir) and works on all that the one before kept; all but the last return the
columns of documents. Between stages the rows are written as Parquet in the shared folder and read
again, so a lost executor never costs an earlier stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from linefault.llm.common import staged, table
from linefault.llm.exact_dedup import exact_dedup
from linefault.llm.mixing import mix_sources
from linefault.llm.ngram_join import drop_near_duplicates
from linefault.llm.packing import pack
from linefault.llm.quality import keep_quality


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier accepts; it learns from the labels of this table's documents.

    Null text counts as empty and is scored like any; a very long text is scored whole; equal texts get equal scores, so ties
    and repeated rows stay or go together; without usable labels every score is 0.5 and all rows stay; an empty table gives an
    empty one; other columns, whatever their names, are kept.
    """
    return keep_quality(docs, table(spark, sf_dir, "labels"))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts (A-Z lower-cased) the row with the largest doc_id.

    Null text equals the empty one; texts are compared whole, however long; a null doc_id is the smallest; of rows that tie in
    doc_id one stays; an empty table gives an empty one; other columns, whatever their names, are kept.
    """
    return exact_dedup(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates: the one with the smallest doc_id.

    Null text is empty; texts without words are a class each by equality alone, shorter ones than five words have their whole
    word sequence as their n-gram, and very long ones are taken whole; a null doc_id is the largest; repeated rows are one class; an
    empty table gives an empty one; other columns, whatever their names, are kept.
    """
    return drop_near_duplicates(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its source's target weight takes it.

    Null source is a source of its own; null and empty texts weigh nothing and follow their source's rate; a text longer than
    its source's target is taken whole or not; rows that share a doc_id are drawn one by one and a null doc_id like any; an empty
    table gives an empty one; other columns, whatever their names, are kept.
    """
    return mix_sources(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their place in fixed windows.

    Null and empty texts are their end token alone; a text longer than a window is cut into pieces; repeated rows and rows with
    a null doc_id are documents of their own; an empty table gives no pieces; only doc_id and text are read.
    """
    return pack(docs)


STAGES = [("quality", quality_stage), ("exact_dedup", exact_stage), ("near_dedup", near_stage), ("mixing", mixing_stage), ("packing", packing_stage)]

#: The discriminant, the banding and the packing plan have no SQL; tests/llm holds the brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = staged(docs, name)
    return docs
