"""Anonymity: block sizes, candidates with equal features, overlap of releases; agreement of labelings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import both_ways, degrees


def anonymity_level(labels: DataFrame) -> DataFrame:
    """Members of the smallest non-empty block."""
    return labels.groupBy("lab").agg(F.count("*").alias("n")).agg(F.min("n").alias("level"))


def reid_bound(labels: DataFrame) -> DataFrame:
    """Mean and largest chance of picking the right member of a block at random."""
    sizes = labels.groupBy("lab").agg(F.count("*").alias("n"))
    return sizes.agg((F.count("*") / F.sum("n")).alias("mean_bound"), (1 / F.min("n")).alias("max_bound"))


def candidates(features: DataFrame, feature: str) -> DataFrame:
    """id and how many vertices share its feature: a count by feature first, so a common one is no hot window."""
    sizes = features.groupBy(feature).agg(F.count("*").alias("candidates"))
    return features.join(sizes, feature).select("id", feature, "candidates")


def degree_candidates(edges: DataFrame) -> DataFrame:
    return candidates(degrees(edges), "deg")


def neighbour_signatures(edges: DataFrame) -> DataFrame:
    """id, signature: md5 of the sorted degrees of a vertex's neighbours."""
    deg = degrees(edges).select(F.col("id").alias("other"), "deg")
    seen = both_ways(edges).join(deg, "other").groupBy("id").agg(F.sort_array(F.collect_list("deg")).alias("d"))
    return seen.select("id", F.md5(F.array_join(F.transform("d", lambda x: x.cast("string")), ",")).alias("signature"))


def edge_overlap(released: DataFrame, original: DataFrame) -> DataFrame:
    """Released edges, those that exist in the original, and their share."""
    met = released.select("src", "dst").join(original.select("src", "dst").withColumn("hit", F.lit(1)), ["src", "dst"], "left")
    return met.agg(F.count("*").alias("released"), F.count("hit").alias("shared")).withColumn("share", F.coalesce(F.try_divide("shared", "released"), F.lit(0.0)))


def contingency(one: DataFrame, other: DataFrame) -> DataFrame:
    return one.select("id", F.col("lab").alias("x")).join(other.select("id", F.col("lab").alias("y")), "id").groupBy("x", "y").agg(F.count("*").alias("n"))


def nmi(one: DataFrame, other: DataFrame) -> DataFrame:
    """Mutual information over the mean of the two entropies."""
    cells = contingency(one, other)
    rows, columns = cells.groupBy("x").agg(F.sum("n").alias("nx")), cells.groupBy("y").agg(F.sum("n").alias("ny"))
    whole = cells.agg(F.sum("n").cast("double").alias("t"))
    h = lambda side, n: side.join(F.broadcast(whole)).agg(F.sum(-(F.col(n) / F.col("t")) * F.ln(F.col(n) / F.col("t"))).alias(f"h{n}"))
    mutual = cells.join(rows, "x").join(columns, "y").join(F.broadcast(whole)).agg(F.sum(F.col("n") / F.col("t") * F.ln(F.col("n") * F.col("t") / (F.col("nx") * F.col("ny")))).alias("mi"))
    return mutual.join(h(rows, "nx")).join(h(columns, "ny")).select(F.coalesce(F.try_divide(2 * F.col("mi"), F.col("hnx") + F.col("hny")), F.lit(1.0)).alias("nmi"))


def ari(one: DataFrame, other: DataFrame) -> DataFrame:
    """Pair agreement corrected for chance."""
    cells = contingency(one, other)
    pairs = lambda c: c.cast("double") * (c - 1) / 2
    a = cells.groupBy("x").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("a"))
    b = cells.groupBy("y").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("b"))
    both = cells.agg(F.sum(pairs(F.col("n"))).alias("s"), pairs(F.sum("n")).alias("t"))
    met = both.join(a).join(b).withColumn("e", F.col("a") * F.col("b") / F.col("t"))
    return met.select(F.coalesce(F.try_divide(F.col("s") - F.col("e"), (F.col("a") + F.col("b")) / 2 - F.col("e")), F.lit(1.0)).alias("ari"))
