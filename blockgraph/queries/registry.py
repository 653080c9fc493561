"""All queries of the engine and their DuckDB twins, gathered from the query modules."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import hard, measures, relational, soft, workloads  # noqa: F401  register their queries
from .base import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "flagship"]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return QUERIES["hard_fit_trace"](spark, sf_dir)
