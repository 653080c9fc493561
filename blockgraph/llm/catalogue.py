"""Queries of the training-data operators, by driver contract, and their DuckDB twins where SQL has one."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat_format, line_dedup
from ._common import table

QUERIES: dict = {}
ORACLES: dict = {}


def _query(f):
    QUERIES[f.__name__] = f
    return f


@_query
def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language_id import identify

    return identify(spark, table(spark, sf_dir, "documents"))


@_query
def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_counts import token_counts

    return token_counts(table(spark, sf_dir, "documents"))


@_query
def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substring_dedup import digest, repeated_words

    return digest(repeated_words(table(spark, sf_dir, "documents")))


@_query
def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_dedup import digest, repeated_bytes

    return digest(repeated_bytes(table(spark, sf_dir, "documents")))


@_query
def op7_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .near_dedup import digest, near_duplicates

    return digest(near_duplicates(spark, table(spark, sf_dir, "documents")))


@_query
def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.digest(line_dedup.dedup_lines(table(spark, sf_dir, "documents")))


ORACLES["op10_line_dedup"] = line_dedup.ORACLE


@_query
def op10_line_dedup_long_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runs of lines, and lines of LONG_WORDS words and more on their own."""
    return line_dedup.digest(line_dedup.dedup_lines(table(spark, sf_dir, "documents"), long_words=line_dedup.LONG_WORDS))


@_query
def op1_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_format.digest(chat_format.formatted(table(spark, sf_dir, "conversations")))


ORACLES["op1_chat_format"] = chat_format.ORACLE


@_query
def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontamination import contaminated

    return contaminated(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


@_query
def op8_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .top_k import top_k

    return top_k(spark, table(spark, sf_dir, "embeddings"), F.pmod("vec_id", F.lit(100)) == 0)


@_query
def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack_documents

    return pack_documents(table(spark, sf_dir, "documents"))
