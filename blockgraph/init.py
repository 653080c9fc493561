"""Starting points: random memberships, category tensors and labels, all functions of ids."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .rng import portable


def normalised(vec: Column) -> Column:
    total = F.aggregate(vec, F.lit(0.0), lambda s, x: s + x)
    return F.transform(vec, lambda x: x / total)


def random_mem(ids: DataFrame, blocks: int, seed: int, side: str = "l") -> DataFrame:
    """id, vec: a row of `blocks` positive numbers that add up to 1."""
    raw = F.array(*[portable(seed, f"mem{side}", F.col("id"), a) + 0.05 for a in range(blocks)])
    return ids.select("id", normalised(raw).alias("vec"))


def random_cat(spark: SparkSession, a_blocks: int, b_blocks: int, categories: int, seed: int) -> DataFrame:
    """a, b, c, p: for each block pair a distribution over categories 0 .. categories - 1."""
    grid = spark.range(a_blocks * b_blocks).select((F.col("id") / b_blocks).cast("int").alias("a"), (F.col("id") % b_blocks).cast("int").alias("b"))
    raw = F.array(*[portable(seed, "cat", F.col("a"), F.col("b"), c) + 0.05 for c in range(categories)])
    return grid.select("a", "b", F.posexplode(normalised(raw)).alias("c", "p"))


def random_cat_of(categories: DataFrame, a_blocks: int, b_blocks: int, seed: int) -> DataFrame:
    """The same over given categories, one row a category c; equal to random_cat where these are 0 .. categories - 1."""
    grid = categories.sparkSession.range(a_blocks * b_blocks).select((F.col("id") / b_blocks).cast("int").alias("a"), (F.col("id") % b_blocks).cast("int").alias("b"))
    raw = categories.select(F.col("c").cast("int").alias("c")).crossJoin(F.broadcast(grid)).withColumn("u", portable(seed, "cat", F.col("a"), F.col("b"), F.col("c")) + 0.05)
    return raw.select("a", "b", "c", (F.col("u") / F.sum("u").over(W.partitionBy("a", "b"))).alias("p"))


def random_labels(ids: DataFrame, n_blocks: int, seed: int) -> DataFrame:
    return ids.select("id", F.floor(portable(seed, "label", F.col("id")) * n_blocks).cast("int").alias("lab"))


def balanced_labels(ids: DataFrame, n_blocks: int, seed: int) -> DataFrame:
    """Labels of equal block sizes (up to one): ranks of a hash, by hash ranges first so that no task sorts all ids."""
    u = portable(seed, "balanced", F.col("id"))
    coarse = ids.select("id", u.alias("u"), F.floor(u * 256).cast("int").alias("range"))
    before = coarse.groupBy("range").agg(F.count("*").alias("n")).withColumn("before", F.coalesce(F.sum("n").over(W.orderBy("range").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    ranked = coarse.join(F.broadcast(before), "range").withColumn("rank", F.row_number().over(W.partitionBy("range").orderBy("u", "id")) - 1 + F.col("before"))
    return ranked.select("id", F.pmod(F.col("rank"), F.lit(n_blocks)).cast("int").alias("lab"))
