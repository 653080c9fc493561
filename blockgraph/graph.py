"""Edge tables: validation, canonical form, categories, vertices."""

from __future__ import annotations

from enum import Enum

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class EdgeFamily(Enum):
    BERNOULLI = "bernoulli"
    BINOMIAL = "binomial"
    MULTINOMIAL = "multinomial"


def validate_edges(edges: DataFrame, *more: str) -> DataFrame:
    """edges with src, dst and the named columns as long ids; fails on missing columns."""
    missing = {"src", "dst", *more} - set(edges.columns)
    if missing:
        raise ValueError(f"edges lack {sorted(missing)}")
    return edges.where(F.col("src").isNotNull() & F.col("dst").isNotNull()).withColumns({"src": F.col("src").cast("long"), "dst": F.col("dst").cast("long")})


def canonical(edges: DataFrame) -> DataFrame:
    """A simple undirected graph: src < dst, no loops, no repeats."""
    return edges.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()


def both_ways(edges: DataFrame, *more: str) -> DataFrame:
    """(id, other, ...) for both ends of each edge."""
    there = edges.select(F.col("src").alias("id"), F.col("dst").alias("other"), *more)
    return there.unionAll(edges.select(F.col("dst").alias("id"), F.col("src").alias("other"), *more))


def vertices(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("id")).unionAll(edges.select(F.col("dst").alias("id"))).distinct()


def degrees(edges: DataFrame) -> DataFrame:
    return both_ways(edges).groupBy("id").agg(F.count("*").alias("deg"))


def categorise(value: Column, bounds: list[float]) -> Column:
    """Number of bounds at or below a value: a category from 0 to len(bounds)."""
    return sum((F.when(value >= b, 1).otherwise(0) for b in bounds), F.lit(0)).cast("int")


def rating_category(mean_quantity: Column, step: float = 10.0, top: int = 5) -> Column:
    return F.least(F.greatest(F.ceil(mean_quantity / step), F.lit(1)), F.lit(top)).cast("int")
