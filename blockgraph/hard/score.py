"""Move scores of vertices: table (sparse corrections of cost tables), plugin (frozen probabilities), exact."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.placement import pairs_table
from .stats import c_log, cost_tables, full_pairs, pair_cost

EPS = 1e-9


def _touched(links: DataFrame, labels: DataFrame) -> DataFrame:
    """id, y (own block), b, x over blocks a vertex touches and its own block, with x = 0 where it has no link there."""
    own = labels.select("id", F.col("lab").alias("y"))
    seen = links.join(own, "id")
    return seen.unionByName(own.select("id", "y", F.col("y").alias("b"), F.lit(0).cast("long").alias("x"))).groupBy("id", "y", "b").agg(F.sum("x").alias("x"))


def score_rows(links: DataFrame, labels: DataFrame, tables: DataFrame, own_side: bool, n_blocks: int | None = None) -> DataFrame:
    """id, a, score by cost tables(a, b, nb, hit, miss, enter, leave) corrected for the blocks a vertex touches.

    own_side: the partners are on the vertex's side, which is no partner of itself.
    """
    totals = tables.groupBy("a").agg(F.sum("enter").alias("enter_all"), F.sum("leave").alias("leave_all"))
    x, hit, miss = F.col("x").cast("double"), F.col("hit"), F.col("miss")
    partners = F.col("nb") - F.when(F.col("b") == F.col("y"), 1).otherwise(0) if own_side else F.col("nb")
    apart = partners - x
    own, now = F.col("a") == F.col("y"), pair_cost(hit, miss, c_log)
    sign = F.when(own, -1.0).otherwise(1.0)
    after = pair_cost(hit + sign * x, miss + sign * apart, c_log)
    change = F.when(own, now - after - F.col("leave")).otherwise(after - now - F.col("enter"))
    touched = _touched(links, labels) if own_side else _rooted(links, labels)
    corrected = touched.join(pairs_table(tables, n_blocks), "b").groupBy("id", "y", "a").agg(F.sum(change).alias("correction"))
    base = F.when(F.col("a") == F.col("y"), F.col("leave_all")).otherwise(F.col("enter_all"))
    return corrected.join(pairs_table(totals, n_blocks), "a").select("id", "y", "a", (base + F.col("correction")).alias("score"))


def _rooted(links: DataFrame, labels: DataFrame) -> DataFrame:
    """_touched() with the first block of the other side, so that vertices without links are scored too."""
    own = labels.select("id", F.col("lab").alias("y"))
    seen = links.join(own, "id")
    return seen.unionByName(own.select("id", "y", F.lit(0).alias("b"), F.lit(0).cast("long").alias("x"))).groupBy("id", "y", "b").agg(F.sum("x").alias("x"))


def score_table(links: DataFrame, labels: DataFrame, stats: DataFrame, n_blocks: int | None = None) -> DataFrame:
    """id, a, score: cost of having each vertex in block a, by cost tables corrected for the blocks it touches.

    links and labels hold the vertices to score; the tables have one row a block pair.
    """
    return score_rows(links, labels, cost_tables(stats), True, n_blocks)


def score_plugin(links: DataFrame, labels: DataFrame, stats: DataFrame, n_blocks: int | None = None) -> DataFrame:
    """The same by frozen block probabilities: -sum of x ln p + (partners - x) ln(1 - p)."""
    p = F.greatest(F.lit(EPS), F.least(F.lit(1 - EPS), F.try_divide(F.col("hit"), F.col("pairs"))))
    tables = full_pairs(stats).select("a", "b", "nb", F.ln(F.coalesce(p, F.lit(EPS))).alias("lp"), F.ln(1 - F.coalesce(p, F.lit(EPS))).alias("lq"))
    totals = tables.groupBy("a").agg(F.sum(-F.col("nb") * F.col("lq")).alias("none"))
    own = F.when(F.col("b") == F.col("y"), 1).otherwise(0)
    change = -F.col("x") * (F.col("lp") - F.col("lq")) + own * F.col("lq")
    touched = _touched(links, labels).join(pairs_table(tables, n_blocks), "b")
    corrected = touched.groupBy("id", "y", "a").agg(F.sum(change).alias("correction"))
    return corrected.join(pairs_table(totals, n_blocks), "a").select("id", "y", "a", (F.col("none") + F.col("correction")).alias("score"))


def score_exact(links: DataFrame, labels: DataFrame, stats: DataFrame, n_blocks: int | None = None) -> DataFrame:
    """Entropy with each vertex in block a, less the entropy without the vertex: exact for single moves.

    All partners of the vertex count, linked or not: each (vertex, block a) meets every block b.
    """
    tables = full_pairs(stats).select("a", "b", "nb", "hit", "miss")
    own = labels.select("id", F.col("lab").alias("y"))
    sizes = tables.groupBy("b").agg(F.max("nb").alias("nb"))
    every = sizes.agg(F.array_sort(F.collect_list(F.struct("b", "nb"))).alias("sizes"))  # one row, as long as there are blocks
    dense = own.join(F.broadcast(every)).select("id", "y", F.inline("sizes")).join(links, ["id", "b"], "left").select("id", "y", "b", F.coalesce("x", F.lit(0)).cast("double").alias("x"), (F.col("nb") - F.when(F.col("b") == F.col("y"), 1).otherwise(0)).cast("double").alias("s"))
    from_own = dense.select("id", F.col("b").alias("other"), F.col("x").alias("xo"), F.col("s").alias("so"))
    cells = dense.join(pairs_table(tables.drop("nb"), n_blocks), "b")
    # counts of the pair (a, b) without the vertex: it had links from its own block y to every block
    cells = cells.join(from_own.withColumnRenamed("other", "a"), ["id", "a"])
    gone_hit = F.when(F.col("a") == F.col("y"), F.col("x")).when(F.col("b") == F.col("y"), F.col("xo")).otherwise(0.0)
    gone_all = F.when(F.col("a") == F.col("y"), F.col("s")).when(F.col("b") == F.col("y"), F.col("so")).otherwise(0.0)
    hit, miss = F.col("hit") - gone_hit, F.col("miss") - (gone_all - gone_hit)
    change = pair_cost(hit + F.col("x"), miss + F.col("s") - F.col("x"), c_log) - pair_cost(hit, miss, c_log)
    return cells.groupBy("id", "y", "a").agg(F.sum(change).alias("score"))


SCORERS = {"table": score_table, "plugin": score_plugin, "exact": score_exact}


def best_moves(scores: DataFrame, margin: float = 1e-9) -> DataFrame:
    """id, lab, gain: the block with the lowest score; the own block unless another is better by more than margin,
    the smallest label among equals."""
    key = F.struct(F.round("score", 9), F.col("a"))
    chosen = scores.groupBy("id", "y").agg(F.min(key).alias("k"), F.max(F.when(F.col("a") == F.col("y"), F.col("score"))).alias("stay"), F.min("score").alias("least"))
    moves = F.col("stay") - F.col("least") > margin
    return chosen.select("id", F.when(moves, F.col("k.a")).otherwise(F.col("y")).cast("int").alias("lab"), F.when(moves, F.col("stay") - F.col("least")).otherwise(0.0).alias("gain"), "y")
