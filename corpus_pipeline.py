"""Corpus pipeline: five stages from raw documents to packed training sequences, each by one operator of blockgraph.llm.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; its result is written and read back before the next.
All stages but the last return the columns of documents. A document leaves for good when its language is not
recognised, when line dedup takes all its lines, when a smaller document of its near-duplicate group stays, or when it
holds a benchmark item. SQL cannot express the stages, so there is no ORACLE_SQL; tests compare with brute force.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from blockgraph.llm import decontamination, language_id, line_dedup, near_dedup, packing
from blockgraph.llm._common import forget, materialise, table
from blockgraph.session import ship


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose language is recognised."""
    ship(spark)
    return language_id.confident(spark, docs)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Deletes later copies of repeated runs of lines."""
    ship(spark)
    return line_dedup.without_repeats(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest document of each near-duplicate group."""
    ship(spark)
    return near_dedup.one_of_each(spark, docs)


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark item."""
    ship(spark)
    return decontamination.clean(spark, docs, table(spark, sf_dir, "benchmark"))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places documents into sequences: doc_id, piece, length, bin, start."""
    ship(spark)
    return packing.pack_documents(docs)


STAGES = [
    ("language_id", language_stage),
    ("line_dedup", line_stage),
    ("near_dedup", near_stage),
    ("decontamination", benchmark_stage),
    ("packing", packing_stage),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), name)
        if before is not None:
            forget(before)
        before = docs
    return docs
