"""Scans of the given tables and the graphs built from them, with DuckDB twins of each graph."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import canonical, rating_category
from ..plans.drawn import pairs_drawn
from ..plans.meetings import shared_groups
from ..plans.similar import similar_pairs
from ..plans.state import write_state
from ..rng import portable, portable_sql

PROPS = "k int"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def g1_copurchase(spark: SparkSession, sf_dir: str, among: DataFrame | None = None) -> DataFrame:
    """Parts that share an order: src < dst, w orders. among: only pairs of these parts (id)."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    if among is not None:
        lines = lines.join(among.select(F.col("id").alias("l_partkey")), "l_partkey", "left_semi")
    other = lines.withColumnRenamed("l_partkey", "dst")
    return lines.withColumnRenamed("l_partkey", "src").join(other, "l_orderkey").where("src < dst").groupBy("src", "dst").agg(F.count("*").alias("w"))


def g1_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return g1_copurchase(spark, sf_dir).where("w >= 2")


def g2_memberships(spark: SparkSession, sf_dir: str) -> DataFrame:
    """member, grp: users and the (props, day) they were seen with, as a written table; groups are numbered."""
    seen = table(spark, sf_dir, "events").select("user_id", "props", F.to_date("ts").alias("day")).dropna().distinct()
    groups = write_state(seen.select("props", "day").distinct().withColumn("grp", F.monotonically_increasing_id()), "groups")
    return write_state(seen.join(groups, ["props", "day"]).select(F.col("user_id").alias("member"), "grp"), "memberships")


def g2_coactivity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users with the same props on the same day."""
    return shared_groups(g2_memberships(spark, sf_dir))


def g3_similarity(spark: SparkSession, sf_dir: str, least: float = 0.3) -> DataFrame:
    """Pairs of embeddings whose inner product exceeds `least`: blocks of vectors against blocks of vectors."""
    return similar_pairs(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec")), least)


def rating_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey)


def g4_rating(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer x part with a rating 1..5 from the mean quantity; w units in 50 trials a line."""
    pairs = rating_lines(spark, sf_dir).groupBy(F.col("o_custkey").alias("src"), F.col("l_partkey").alias("dst"))
    mean = F.avg("l_quantity")
    return pairs.agg(rating_category(mean).alias("cat"), F.sum("l_quantity").cast("long").alias("w"), (F.count("*") * 50).alias("trials"))


def g5_like(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rating_lines(spark, sf_dir).select(F.col("o_custkey").alias("src"), F.col("l_suppkey").alias("dst")).distinct()


def g5_part_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst")).distinct()


def g6_user_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events").select(F.col("user_id").alias("src"), F.from_json("props", PROPS)["k"].cast("long").alias("dst"))
    return events.where("dst IS NOT NULL").distinct()


def g6_user_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("user_id", "event_type").distinct()


def g7_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer nation -> supplier nation, number of lines; directed, with loops."""
    customer = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("src"))
    supplier = table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("dst"))
    counted = rating_lines(spark, sf_dir).groupBy("o_custkey", "l_suppkey").agg(F.count("*").alias("n"))
    return counted.join(customer, counted.o_custkey == customer.c_custkey).join(supplier, counted.l_suppkey == supplier.s_suppkey).groupBy("src", "dst").agg(F.sum("n").alias("w"))


def g8_transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event type -> next event type of the same user."""
    from pyspark.sql import Window as W

    nxt = F.lead("event_type").over(W.partitionBy("user_id").orderBy("ts", "event_id"))
    steps = table(spark, sf_dir, "events").select(F.col("event_type").alias("src"), nxt.alias("dst"))
    return steps.where("dst IS NOT NULL").groupBy("src", "dst").agg(F.count("*").alias("w"))


def g9_page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page x link target: distinct href values."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target"))
    return pages.distinct()


def g10_urgency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Market segment - order priority, where the segment has more such orders than the mean pair: segments have even
    ids and priorities odd ones, both by name."""
    customer = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_mktsegment").alias("s"))
    orders = table(spark, sf_dir, "orders").select("o_custkey", F.col("o_orderpriority").alias("p"))
    counted = orders.join(customer, orders.o_custkey == customer.c_custkey).where("s IS NOT NULL AND p IS NOT NULL").groupBy("s", "p").agg(F.count("*").alias("n"))
    counts = F.array_sort(F.collect_list(F.struct("s", "p", "n")))  # one row: a pair of names is a row
    every = counted.agg(counts.alias("c"), F.array_sort(F.collect_set("s")).alias("ss"), F.array_sort(F.collect_set("p")).alias("ps"), F.avg("n").alias("mean"))
    rows = every.select("ss", "ps", "mean", F.inline("c")).where("n > mean")
    return rows.select((2 * F.array_position("ss", F.col("s")) - 2).cast("long").alias("src"), (2 * F.array_position("ps", F.col("p")) - 1).cast("long").alias("dst"))


def planted_simple(spark: SparkSession, sf_dir: str, inside: float = 0.02, across: float = 0.001, blocks: int = 8, seed: int = 42) -> DataFrame:
    """A graph over part keys with blocks key mod `blocks`: pairs drawn by hash. Quadratic, for fixtures."""
    kinds = 2 * blocks - 1  # a remainder has the sign of its key
    chances = np.where(np.eye(kinds, dtype=bool), inside, across)
    return pairs_drawn(table(spark, sf_dir, "part"), "p_partkey", F.col("p_partkey") % blocks + (blocks - 1), chances, seed, "p1")


def g1_heavy(spark: SparkSession, sf_dir: str, wanted: int, gamma: float = 0.8, seed: int = 1) -> DataFrame:
    """About `wanted` edges of the co-purchase graph with heavy-tailed degrees: a part has a rank by hash and the weight
    rank^-gamma, an edge stays with a chance in proportion to both weights."""
    edges = g1_copurchase(spark, sf_dir).select("src", "dst")
    n = table(spark, sf_dir, "part").count()
    weight = lambda c: F.pow(F.floor(portable(seed, "heavy", F.col(c)) * n) + 1, F.lit(-gamma))
    weighed = write_state(edges.withColumn("w", weight("src") * weight("dst")), "weighed")  # read seven times
    scale = 1.0
    for _ in range(6):  # chances end at 1, so the scale is found by repetition
        kept = weighed.agg(F.sum(F.least(F.lit(1.0), F.col("w") * scale))).first()[0]
        if not kept:
            break
        scale *= wanted / kept
    return weighed.where(portable(seed, "heavyedge", F.col("src"), F.col("dst")) < F.col("w") * scale).select("src", "dst")


def planted_rating(spark: SparkSession, sf_dir: str, keep: float = 0.7, seed: int = 42) -> DataFrame:
    """The pairs of g4 with ratings from planted blocks src mod 4, dst mod 3."""
    block = (2 * (F.col("src") % 4) + 3 * (F.col("dst") % 3)) % 5 + 1
    noise = F.floor(portable(seed, "p2cat", F.col("src"), F.col("dst")) * 5) + 1
    rating = F.when(portable(seed, "p2keep", F.col("src"), F.col("dst")) < keep, block).otherwise(noise)
    return g4_rating(spark, sf_dir).select("src", "dst", rating.cast("int").alias("cat"))


def planted_points(spark: SparkSession, sf_dir: str, shift: float = 0.5, seed: int = 42) -> DataFrame:
    """embeddings moved by a hash centre of their label: id, vec, lab."""
    moved = F.transform("embedding", lambda x, i: x.cast("double") + shift * (portable(seed, "p3", F.col("label"), i) * 2 - 1))
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), moved.alias("vec"), F.col("label").alias("lab"))


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"))


def simple(edges: DataFrame) -> DataFrame:
    return canonical(edges)


G1 = "SELECT a.l_partkey AS src, b.l_partkey AS dst, count(DISTINCT a.l_orderkey) AS w FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2"
G1S = f"SELECT * FROM ({G1}) WHERE w >= 2"
G2 = """SELECT a.user_id AS src, b.user_id AS dst, count(*) AS w FROM (SELECT DISTINCT user_id, props, CAST(ts AS DATE) AS day FROM events) a
JOIN (SELECT DISTINCT user_id, props, CAST(ts AS DATE) AS day FROM events) b ON a.props = b.props AND a.day = b.day AND a.user_id < b.user_id GROUP BY 1, 2"""
G3 = """SELECT a.vec_id AS src, b.vec_id AS dst, list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda x: CAST(x[1] AS DOUBLE) * CAST(x[2] AS DOUBLE))) AS cos
FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id"""
G4 = """SELECT o_custkey AS src, l_partkey AS dst, CAST(least(greatest(ceil(avg(l_quantity) / 10), 1), 5) AS INTEGER) AS cat,
CAST(sum(l_quantity) AS BIGINT) AS w, count(*) * 50 AS trials FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2"""
G5 = "SELECT DISTINCT o_custkey AS src, l_suppkey AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
G5B = "SELECT DISTINCT l_partkey AS src, l_suppkey AS dst FROM lineitem"
G6 = "SELECT DISTINCT user_id AS src, CAST(json_extract(props, '$.k') AS BIGINT) AS dst FROM events WHERE json_extract(props, '$.k') IS NOT NULL"
G6T = "SELECT DISTINCT user_id, event_type FROM events"
G7 = """SELECT CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey
JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2"""
G8 = """SELECT src, dst, count(*) AS w FROM (SELECT event_type AS src, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events)
WHERE dst IS NOT NULL GROUP BY 1, 2"""
G9 = "SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS target FROM pages"

G10 = """SELECT CAST(2 * dense_rank() OVER (ORDER BY s) - 2 AS BIGINT) AS src, CAST(2 * dense_rank() OVER (ORDER BY p) - 1 AS BIGINT) AS dst
FROM (SELECT c_mktsegment AS s, o_orderpriority AS p, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment IS NOT NULL AND o_orderpriority IS NOT NULL GROUP BY 1, 2) QUALIFY n > avg(n) OVER ()"""


def p1_sql(inside: float = 0.02, across: float = 0.001, blocks: int = 8, seed: int = 42) -> str:
    u = portable_sql(seed, "p1", "a.p_partkey", "b.p_partkey")
    return f"SELECT a.p_partkey AS src, b.p_partkey AS dst FROM part a JOIN part b ON a.p_partkey < b.p_partkey WHERE {u} < CASE WHEN a.p_partkey % {blocks} = b.p_partkey % {blocks} THEN {inside} ELSE {across} END"


def p2_sql(keep: float = 0.7, seed: int = 42) -> str:
    kept, noise = portable_sql(seed, "p2keep", "src", "dst"), portable_sql(seed, "p2cat", "src", "dst")
    return f"SELECT src, dst, CAST(CASE WHEN {kept} < {keep} THEN (2 * (src % 4) + 3 * (dst % 3)) % 5 + 1 ELSE floor({noise} * 5) + 1 END AS INTEGER) AS cat FROM ({G4})"
