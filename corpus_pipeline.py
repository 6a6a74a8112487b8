"""A corpus from raw documents to packed token sequences, in five stages.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before it
kept; all but the last return the columns of ``documents``. Between stages the
table is written to the shared folder and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from graphkw.llm.base import Stage, table
from graphkw.llm.decontaminate import drop_contaminated, load_tests
from graphkw.llm.line_dedup import dedup_lines
from graphkw.llm.minhash import drop_near_duplicates
from graphkw.llm.packing import pack_documents
from graphkw.llm.quality_knn import fit_quality, keep_good


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that the classifier rejects; null and empty texts are scored like any other. An empty table stays empty."""
    return keep_good(docs, fit_quality(docs, table(spark, sf_dir, "labels")))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one of each group of alike lines; documents stay even without lines, null texts stay null."""
    return dedup_lines(docs).select(docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group; texts without words, rows that repeat an id and text, and rows with a null doc_id all stay."""
    return drop_near_duplicates(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that hold a passage of a benchmark item; null texts and null items match nothing."""
    return drop_contaminated(docs, load_tests(table(spark, sf_dir, "benchmark")))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into sequences; a null or empty text is one end token."""
    return pack_documents(docs)


STAGES = [
    ("quality_classifier", quality),
    ("line_dedup", lines),
    ("minhash_dedup", near_duplicates),
    ("decontamination", decontamination),
    ("packing", packing),
]
#: SQL has no tokenizer; the stages are tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = Stage(stage(spark, docs, sf_dir), name).df
    return STAGES[-1][1](spark, docs, sf_dir)
