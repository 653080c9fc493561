"""How tables meet: broadcast behind a size check, grid placement of edges, bucket samples, salted sums."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BROADCAST_BYTES = 64 << 20
FEW = 100_000


def by_rows(df: DataFrame, rows: int | None = None) -> DataFrame:
    """A hint from the number of rows: broadcast up to FEW, else (or if unknown) sorted and merged. The planner goes by the
    bytes of a file, and ids that compress well make millions of rows look small enough for the driver."""
    return F.broadcast(df) if rows is not None and rows <= FEW else df.hint("merge")


def small_or_shuffled(df: DataFrame, rows: int, bytes_per_row: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """A broadcast hint if rows * bytes_per_row stays under the limit; else df as it is, to be shuffled."""
    return F.broadcast(df) if rows * bytes_per_row <= limit else df


def pairs_table(df: DataFrame, n_blocks: int | None) -> DataFrame:
    """A table with a row a block pair: broadcast if its size is known and small, else left to the planner."""
    return df if n_blocks is None else small_or_shuffled(df, n_blocks * n_blocks, 64)


def grid(edges: DataFrame, side: int) -> DataFrame:
    """Edges dealt on a side x side grid of vertex hashes: each vertex table row is needed by `side` cells only."""
    cell = lambda c: F.pmod(F.xxhash64(c), F.lit(side)).cast("int")
    return edges.withColumns({"su": cell("src"), "sv": cell("dst")}).repartition(side * side, "su", "sv")


def replicate_for_grid(states: DataFrame, side: int, key: str, end: str) -> DataFrame:
    """A vertex table copied once for each cell of its row (end='src') or column (end='dst') of the grid."""
    own, other = ("su", "sv") if end == "src" else ("sv", "su")
    return states.withColumn(own, F.pmod(F.xxhash64(key), F.lit(side)).cast("int")).withColumn(other, F.explode(F.sequence(F.lit(0), F.lit(side - 1))))


def bucket_sample(frac: float, buckets: int, round_: int, key: Column) -> Column:
    """Whole hash buckets instead of single items: about frac of them, another set each round."""
    chosen = max(1, round(frac * buckets))
    return F.pmod(F.xxhash64(key) + F.lit(round_ * chosen), F.lit(buckets)) < chosen


def salted_sum(df: DataFrame, keys: list[str], value: str, salt: Column, salts: int) -> DataFrame:
    """sum(value) by keys in two steps, so that a hub's rows meet in `salts` tasks first."""
    first = df.withColumn("__salt", F.pmod(F.xxhash64(salt), F.lit(salts))).groupBy(*keys, "__salt").agg(F.sum(value).alias("__part"))
    return first.groupBy(*keys).agg(F.sum("__part").alias(value))
