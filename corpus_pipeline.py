"""A corpus pipeline of five stages over documents, each on all that the one before it kept.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes each result as Parquet in the
shared folder and rereads it for the next. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pacedfl.llm.byte_bpe import bpe_documents
from pacedfl.llm.common import table, written
from pacedfl.llm.decontaminate import without_leaks
from pacedfl.llm.quality import fit_quality_model, graded_labels, select_documents
from pacedfl.llm.queries import vocabulary
from pacedfl.llm.secret_scan import redact_secrets
from pacedfl.llm.similar_dedup import near_components, one_of_each_group


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the ordinal classifier selects."""
    return select_documents(docs, fit_quality_model(docs, graded_labels(table(spark, sf_dir, "labels"))))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group: SimHash by pivot tables, as op4_simhash, and a similarity of 0.8."""
    return one_of_each_group(docs, groups_of=near_components)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark item."""
    return without_leaks(docs, table(spark, sf_dir, "benchmark"))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, secrets replaced by a mark."""
    return redact_secrets(docs, *vocabulary())


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, and digests of the ids and of what they decode to."""
    return bpe_documents(docs, *vocabulary(), with_ids=True)


STAGES = [("quality", quality), ("near_dedup", near_dedup), ("decontamination", decontamination), ("secrets", secrets), ("tokens", tokens)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), name)
    return docs
