"""The corpus pipeline: quality, exact copies, near copies, mixing, packing.

A stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written and read again as the
next stage's docs. All but the last keep the columns of documents.

Null texts count as empty and are scored, grouped and packed like empty ones (mixing takes none of
them, as they have no words); null ids, sources and languages are values of their own; rows that
repeat an id are rows of their own; further columns go through unchanged; an empty table gives an
empty table at every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sparsecert.llm.common import load, staged
from sparsecert.llm.exactdedup import without_copies
from sparsecert.llm.mixing import mixed_documents
from sparsecert.llm.neardup import one_of_each
from sparsecert.llm.packing import pack
from sparsecert.llm.quality import accepted


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go, null and empty texts by their score like others."""
    return accepted(docs, load(spark, sf_dir, "labels"))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each class of equal texts stays; null and blank texts are one class."""
    return without_copies(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of similar texts stays; texts without a word stand alone."""
    return one_of_each(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row per document and epoch that the mix takes; the last one of a source is cut to its words. Documents without a word aren't taken."""
    return mixed_documents(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token sequences: a row per piece; a null or empty text is a piece of one end id."""
    return pack(docs)


STAGES = [("quality", quality_stage), ("exact_copies", exact_stage), ("near_copies", near_stage), ("mixing", mixing_stage), ("packing", packing_stage)]

#: SQL can express none of the classifier, the weighted sampling, the vocabulary and the packing.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
