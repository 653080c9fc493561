"""Sufficient statistics of a labeling: block sizes, possible pairs, hits, misses, vertex links, and their entropy."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import both_ways


def c_log(x: Column) -> Column:
    """ln by the C library, as DuckDB and the numpy kernel take it; Spark's own differs in the last bit of some values.

    Scores are differences of terms n ln n: with 10^9 pairs a block that bit is 10^-6, and moves and gains show it.
    """

    @F.pandas_udf("double")
    def logs(values: pd.Series) -> pd.Series:
        return pd.Series(np.fromiter(map(math.log, values), float, len(values)))

    return logs(x)


def xlogx(x: Column, log: Callable[[Column], Column] = F.ln) -> Column:
    """x ln x, 0 at 0."""
    return F.when(x > 0, x * log(F.when(x > 0, x).otherwise(1).cast("double"))).otherwise(0.0)


def pair_cost(hit: Column, miss: Column, log: Callable[[Column], Column] = F.ln) -> Column:
    """Entropy of hit edges among hit + miss pairs under their best probability; 0 for impossible counts."""
    hit, miss = hit.cast("double"), miss.cast("double")
    return F.when((hit >= 0) & (miss >= 0), xlogx(hit + miss, log) - xlogx(hit, log) - xlogx(miss, log)).otherwise(0.0)


def blocks(spark: SparkSession, n_blocks: int, name: str = "a") -> DataFrame:
    return spark.range(n_blocks).select(F.col("id").cast("int").alias(name))


def block_sizes(labels: DataFrame, n_blocks: int, name: str = "a") -> DataFrame:
    """a, n for each block, empty ones included."""
    counted = labels.groupBy(F.col("lab").alias(name)).agg(F.count("*").alias("n"))
    return blocks(labels.sparkSession, n_blocks, name).join(counted, name, "left").select(name, F.coalesce("n", F.lit(0)).alias("n"))


def labelled(edges: DataFrame, left: DataFrame, right: DataFrame | None = None) -> DataFrame:
    """edges with the block a of src and b of dst."""
    right = left if right is None else right
    ends = edges.join(left.select(F.col("id").alias("src"), F.col("lab").alias("a")), "src")
    return ends.join(right.select(F.col("id").alias("dst"), F.col("lab").alias("b")), "dst")


def block_pairs(edges: DataFrame, labels: DataFrame, n_blocks: int, right: DataFrame | None = None, right_blocks: int | None = None, directed: bool = False) -> DataFrame:
    """a, b, pairs, hit, miss over all block pairs: a <= b for an undirected graph, all ordered pairs else.

    right: labels of the other side of a bipartite graph. Pair counts are doubles, exact to 2^53 and without overflow.
    """
    ends = labelled(edges, labels, right)
    undirected = right is None and not directed
    if undirected:
        ends = ends.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    hits = ends.groupBy("a", "b").agg(F.count("*").alias("hit"))
    rows = block_sizes(labels, n_blocks, "a").withColumnRenamed("n", "na")
    columns = block_sizes(labels if right is None else right, right_blocks or n_blocks, "b").withColumnRenamed("n", "nb")
    partners = F.sequence(F.col("a") if undirected else F.lit(0), F.lit((right_blocks or n_blocks) - 1))
    grid = rows.withColumn("b", F.explode(partners)).join(columns, "b")
    na, nb = F.col("na").cast("double"), F.col("nb").cast("double")
    own = na * (na - 1) / (2 if undirected else 1)
    pairs = na * nb if right is not None else F.when(F.col("a") == F.col("b"), own).otherwise(na * nb)
    full = grid.join(hits, ["a", "b"], "left").select("a", "b", "na", "nb", pairs.alias("pairs"), F.coalesce("hit", F.lit(0)).alias("hit"))
    return full.withColumn("miss", F.col("pairs") - F.col("hit"))


def simple_entropy(stats: DataFrame) -> DataFrame:
    return stats.agg(F.sum(pair_cost(F.col("hit"), F.col("miss"))).alias("entropy"))


def vertex_links(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """id, b, x: how many edges each vertex has into each block it touches."""
    other = labels.select(F.col("id").alias("other"), F.col("lab").alias("b"))
    return both_ways(edges).join(other, "other").groupBy("id", "b").agg(F.count("*").alias("x"))


def full_pairs(stats: DataFrame) -> DataFrame:
    """Both orders of each block pair of an undirected graph."""
    turned = stats.where("a < b").select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("nb").alias("na"), F.col("na").alias("nb"), "pairs", "hit", "miss")
    return stats.select("a", "b", "na", "nb", "pairs", "hit", "miss").unionAll(turned)


def cost_tables(stats: DataFrame) -> DataFrame:
    """a, b, enter, leave: what an isolated vertex changes when it joins or leaves block a, by partner block b."""
    return cost_rows(full_pairs(stats), True)


def turned_pairs(stats: DataFrame) -> DataFrame:
    """Statistics of ordered block pairs seen from the other end."""
    return stats.select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("nb").alias("na"), F.col("na").alias("nb"), "pairs", "hit", "miss")


def cost_rows(rows: DataFrame, own_side: bool) -> DataFrame:
    """The same for given rows of block pairs; own_side: both blocks are of one side, a vertex is no partner of itself."""
    hit, miss = F.col("hit"), F.col("miss")
    now = pair_cost(hit, miss, c_log)
    fewer = F.col("nb") - F.when(F.col("a") == F.col("b"), 1).otherwise(0) if own_side else F.col("nb")
    return rows.select("a", "b", "na", "nb", "hit", "miss", (pair_cost(hit, miss + F.col("nb"), c_log) - now).alias("enter"), (now - pair_cost(hit, miss - fewer, c_log)).alias("leave"))


def profile_rating_entropy(edges: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Entropy of observed categories: each block pair with its own best category distribution."""
    cells = labelled(edges, left, right).groupBy("a", "b", "cat").agg(F.count("*").cast("double").alias("n"))
    pairs = cells.groupBy("a", "b").agg((xlogx(F.sum("n")) - F.sum(xlogx(F.col("n")))).alias("e"))
    return pairs.agg(F.sum("e").alias("entropy"))


def binomial_entropy(edges: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Entropy of w successes of `trials` on observed edges, without the labeling-free constant."""
    cells = labelled(edges, left, right).groupBy("a", "b").agg(F.sum("w").alias("w"), F.sum(F.col("trials") - F.col("w")).alias("rest"))
    return cells.agg(F.sum(pair_cost(F.col("w"), F.col("rest"))).alias("entropy"))


def with_move(labels: DataFrame, vertex: int, lab: int) -> DataFrame:
    """labels with one vertex moved."""
    return labels.select("id", F.when(F.col("id") == vertex, lab).otherwise(F.col("lab")).cast("int").alias("lab"))
