"""Summaries over replicas and folds."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def replica_summary(metrics: DataFrame, *keys: str) -> DataFrame:
    """Mean and sample standard deviation of value over replicas."""
    return metrics.groupBy(*keys).agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("spread"))


def cross_validate(folds: DataFrame, k: int, fit_and_score: Callable[[DataFrame, DataFrame], float]) -> list[tuple[int, float]]:
    """(fold, score) of each fold, trained on the others."""
    return [(f, fit_and_score(folds.where(F.col("fold") != f), folds.where(F.col("fold") == f))) for f in range(k)]
