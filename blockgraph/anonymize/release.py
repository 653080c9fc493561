"""Release of graphs from block summaries: sizes and densities only, re-expanded into random graphs.

What is released has ids of its own: the members of block a are first(a), first(a) + 1, ...; a member's number says its
block and nothing else, since no original id enters. expand() with member_ranks() is the owner's view of the same graph,
with original ids, for measuring only.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..graph import vertices
from ..hard.stats import block_pairs, block_sizes, full_pairs, pair_cost
from ..plans.drawn import pairs_drawn
from ..plans.placement import by_rows
from ..plans.state import write_state
from ..rng import numpy_uniform, portable

SLICE = 100_000


def summary(edges: DataFrame, labels: DataFrame, n_blocks: int) -> DataFrame:
    """a, b, na, nb, pairs, hit, density of each block pair: all that a release needs."""
    return block_pairs(edges, labels, n_blocks).select("a", "b", "na", "nb", F.col("pairs").cast("long").alias("pairs"), "hit", F.coalesce(F.try_divide("hit", "pairs"), F.lit(0.0)).alias("density"))


def _several(df: DataFrame) -> list[str]:
    """The key of tables that hold several labelings of one graph."""
    return ["graph"] if "graph" in df.columns else []


def summaries(edges: DataFrame, labels: DataFrame, n_blocks: list[int]) -> DataFrame:
    """graph and the rows of summary() for each of several labelings at once: labels has id and labs, an array with a block
    for each labeling. The edges meet the labels twice, however many labelings there are."""
    blocks = edges.sparkSession.createDataFrame(list(enumerate(n_blocks)), "graph int, k int")
    each = lambda df, *more: df.select(F.explode(F.sequence(F.lit(0), F.lit(len(n_blocks) - 1))).alias("graph"), *more)
    ends = edges.join(labels.select(F.col("id").alias("src"), F.col("labs").alias("x")), "src").join(labels.select(F.col("id").alias("dst"), F.col("labs").alias("y")), "dst")
    ends = each(ends, "x", "y").select("graph", F.get("x", "graph").alias("u"), F.get("y", "graph").alias("v"))
    hits = ends.groupBy("graph", F.least("u", "v").alias("a"), F.greatest("u", "v").alias("b")).agg(F.count("*").alias("hit"))
    counted = each(labels, "labs").groupBy("graph", F.get("labs", "graph").alias("a")).agg(F.count("*").alias("n"))
    sizes = F.broadcast(write_state(counted, "sizes"))  # a row a block
    rows = blocks.select("graph", "k", F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("a")).join(sizes, ["graph", "a"], "left").select("graph", "k", "a", F.coalesce("n", F.lit(0)).alias("na"))
    grid = rows.select("graph", "a", "na", F.explode(F.sequence("a", F.col("k") - 1)).alias("b")).join(sizes.select("graph", F.col("a").alias("b"), "n"), ["graph", "b"], "left").withColumn("nb", F.coalesce("n", F.lit(0)))
    na, nb = F.col("na").cast("double"), F.col("nb").cast("double")
    pairs = F.when(F.col("a") == F.col("b"), na * (na - 1) / 2).otherwise(na * nb).cast("long")
    full = grid.join(hits, ["graph", "a", "b"], "left").select("graph", "a", "b", "na", "nb", pairs.alias("pairs"), F.coalesce("hit", F.lit(0)).alias("hit"))
    return full.withColumn("density", F.coalesce(F.try_divide("hit", "pairs"), F.lit(0.0)))


def member_ranks(labels: DataFrame, ranges: int = 256, seed: int = 0) -> DataFrame:
    """a, rank, id: members of each block numbered from 0; by graph, if labels has several.

    In two levels: counts of hash ranges inside each block first, so that a large block is never sorted in one task.
    """
    part, block = F.floor(portable(seed, "rank", F.col("id")) * ranges).cast("int"), [*_several(labels), "a"]
    rows = labels.withColumnRenamed("lab", "a").select(*block, "id", part.alias("part"))
    counts = rows.groupBy(*block, "part").agg(F.count("*").alias("n"))
    before = counts.withColumn("before", F.coalesce(F.sum("n").over(W.partitionBy(*block).orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    inside = F.row_number().over(W.partitionBy(*block, "part").orderBy("id")) - 1
    return rows.join(before.drop("n"), [*block, "part"]).select(*block, (inside + F.col("before")).cast("long").alias("rank"), "id")


def draw_counts(summary_: DataFrame, replicas: int, seed: int, mode: str = "binomial") -> DataFrame:
    """replica, a, b, pairs, na, nb, cnt: edges to draw for each block pair that can have any, drawn in the tasks as a
    function of (seed, replica, a, b); by graph, if the summary has several."""
    more = _several(summary_)
    numbers = F.explode(F.sequence(F.lit(0), F.lit(replicas - 1))).alias("replica")
    rows = summary_.where((F.col("pairs") > 0) & (F.col("hit") > 0)).select(numbers, *[F.col(c).cast("int").alias(c) for c in (*more, "a", "b")], *[F.col(c).cast("long").alias(c) for c in ("pairs", "na", "nb", "hit")], F.least("density", F.lit(1.0)).alias("density"))
    if mode == "fixed_count":
        return rows.select(*more, "replica", "a", "b", "pairs", "na", "nb", F.col("hit").alias("cnt"))

    def draw(batches):
        for frame in batches:
            frame["cnt"] = [int(np.random.default_rng([seed, r.replica, r.a, r.b]).binomial(r.pairs, r.density)) for r in frame.itertuples()]
            yield frame[[*more, "replica", "a", "b", "pairs", "na", "nb", "cnt"]]

    return rows.mapInPandas(draw, "graph int, " * len(more) + "replica int, a int, b int, pairs long, na long, nb long, cnt long")


def _numbered(counts: DataFrame, seed: int) -> DataFrame:
    """replica, a, b, i, j (and graph, if counts has it): cnt distinct pairs of members of each block pair, by a keyed permutation of pair numbers.

    Distinct numbers stay distinct, so no shuffle removes repeats; work and rows grow with the edges, not the pairs.
    """
    slices = counts.where("cnt > 0").withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("cnt") - 1) / SLICE))))
    more = _several(counts)
    return slices.mapInPandas(_draw_pairs(seed, more), "graph int, " * len(more) + "replica int, a int, b int, i long, j long")


def new_ids(summary_: DataFrame) -> DataFrame:
    """a, n, first: the released ids of block a are first .. first + n - 1; one row a block."""
    sizes = summary_.where("a = b").select("a", F.col("na").cast("long").alias("n"))
    before = F.coalesce(F.sum("n").over(W.orderBy("a").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return sizes.select("a", "n", before.alias("first"))


def new_labels(summary_: DataFrame) -> DataFrame:
    """id, lab of the vertices of a release, those without edges included."""
    return new_ids(summary_).where("n > 0").select(F.explode(F.sequence(F.col("first"), F.col("first") + F.col("n") - 1)).alias("id"), F.col("a").alias("lab"))


def released(summary_: DataFrame, counts: DataFrame, seed: int) -> DataFrame:
    """replica, src, dst with new ids: from the summary and the drawn counts alone."""
    firsts = new_ids(summary_).select("a", "first")
    met = _numbered(counts, seed).join(firsts, "a").withColumn("u", F.col("i") + F.col("first")).drop("first")
    met = met.join(firsts.withColumnRenamed("a", "b"), "b").withColumn("v", F.col("j") + F.col("first"))
    return met.select("replica", F.least("u", "v").alias("src"), F.greatest("u", "v").alias("dst"))


def expand(counts: DataFrame, ranks: DataFrame, seed: int) -> DataFrame:
    """replica, src, dst: the owner's view of a release, with the ids that ranks has for the members. Several graphs at once,
    if counts and ranks have them: graph, replica, src, dst."""
    more = _several(counts)
    left = by_rows(ranks.select(*more, F.col("a"), F.col("rank").alias("i"), F.col("id").alias("u")))
    right = by_rows(ranks.select(*more, F.col("a").alias("b"), F.col("rank").alias("j"), F.col("id").alias("v")))
    met = _numbered(counts, seed).join(left, [*more, "a", "i"]).join(right, [*more, "b", "j"])
    return met.select(*more, "replica", F.least("u", "v").alias("src"), F.greatest("u", "v").alias("dst"))


def feistel(index: np.ndarray, size: int, key: tuple[int, ...]) -> np.ndarray:
    """A permutation of 0 .. size - 1 applied to index, by cycle walking."""
    half = int(np.ceil(np.sqrt(size)))
    out, todo = index.astype(np.int64), np.arange(len(index))
    while len(todo):
        left, right = out[todo] // half, out[todo] % half
        for r in range(4):
            mixed = (numpy_uniform(r, right, *key) * half).astype(np.int64)
            left, right = right, (left + mixed) % half
        out[todo] = left * half + right
        todo = todo[out[todo] >= size]
    return out


def unrank(pair: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """The pair i < j of 0 .. size - 1 with a given number, by the triangular root."""
    j = np.floor((1 + np.sqrt(8 * pair.astype(float) + 1)) / 2).astype(np.int64)
    j = np.where(j * (j - 1) // 2 > pair, j - 1, j)
    j = np.where((j + 1) * j // 2 <= pair, j + 1, j)
    return pair - j * (j - 1) // 2, j


def _draw_pairs(seed: int, more: list[str]):
    import pandas as pd

    def draw(batches):
        for batch in batches:
            for r in batch.itertuples():
                first = r.part * SLICE
                index = np.arange(first, min(first + SLICE, r.cnt))
                pair = feistel(index, int(r.pairs), (seed, r.replica, r.a, r.b))
                i, j = unrank(pair, r.na) if r.a == r.b else (pair // r.nb, pair % r.nb)
                yield pd.DataFrame({c: np.int32(getattr(r, c)) for c in more} | {"replica": np.int32(r.replica), "a": np.int32(r.a), "b": np.int32(r.b), "i": i, "j": j})

    return draw


def anonymised(edges: DataFrame, labels: DataFrame, n_blocks: int, seed: int = 1, replicas: int = 5, mode: str = "binomial", min_block: int = 0) -> DataFrame:
    """replica, src, dst: graphs drawn from the blocks of a labeling, with new ids. min_block: blocks below it are
    merged into others first, so that every released vertex has that many equals; fails if there are fewer vertices."""
    if min_block:
        labels = enough_members(edges, labels, n_blocks, min_block)
    whole = write_state(summary(edges, labels, n_blocks), "summary")
    return released(whole, draw_counts(whole, replicas, seed, mode), seed)


def enough_members(edges: DataFrame, labels: DataFrame, n_blocks: int, min_block: int) -> DataFrame:
    """labels whose blocks all have min_block members."""
    labels = merge_until(edges, write_state(labels.select("id", "lab"), "labels"), n_blocks, min_block)
    smallest = labels.groupBy("lab").agg(F.count("*").alias("n")).agg(F.min("n")).first()[0]
    if smallest is not None and smallest < min_block:
        raise ValueError(f"{smallest} vertices cannot make a block of {min_block}")
    return labels


def erdos_renyi(edges: DataFrame, seed: int = 1, replicas: int = 1) -> DataFrame:
    """One block: a uniform random graph with as many expected edges."""
    return anonymised(edges, vertices(edges).withColumn("lab", F.lit(0)), 1, seed, replicas)


def expand_pairwise(summary_: DataFrame, labels: DataFrame, seed: int) -> DataFrame:
    """Every pair decided by its own hash: the quadratic reference for small graphs."""
    known = summary_.select("a", "b", "density").collect()  # a row a block pair
    k = 1 + max([r["b"] for r in known], default=0)
    chances = np.zeros((k, k))
    for r in known:
        chances[r["a"], r["b"]] = chances[r["b"], r["a"]] = r["density"]
    return pairs_drawn(labels, "id", F.col("lab"), chances, seed, "expand")


def expand_soft(mem: DataFrame, density: DataFrame, seed: int) -> DataFrame:
    """Pairs drawn with the probability of soft memberships; quadratic, for small graphs."""
    from ..soft.predict import exists

    one = mem.select(F.col("id").alias("src"))
    pairs = one.join(mem.select(F.col("id").alias("dst")), F.col("src") < F.col("dst"))
    return exists(pairs, mem, mem, density).where(portable(seed, "expandsoft", F.col("src"), F.col("dst")) < F.col("pred")).select("src", "dst")


def merge_cost(stats: DataFrame) -> DataFrame:
    """a, c, change: entropy change of merging block a into block c, for all pairs."""
    full = full_pairs(stats)
    inner = stats.where("a = b").select("a", F.col("pairs").alias("p"), F.col("hit").alias("h"))
    now = full.groupBy("a").agg(F.sum(pair_cost(F.col("hit"), F.col("miss"))).alias("cost"))
    between = full.where("a <> b").select("a", F.col("b").alias("c"), F.col("hit").alias("hx"), F.col("pairs").alias("px"), pair_cost(F.col("hit"), F.col("miss")).alias("cx"))
    rest = full.select(F.col("a"), F.col("b"), "hit", "pairs")
    third = between.select("a", "c").join(F.broadcast(rest), "a").join(F.broadcast(rest.select(F.col("a").alias("c"), "b", F.col("hit").alias("h2"), F.col("pairs").alias("p2"))), ["c", "b"]).where("b <> a AND b <> c")
    merged = third.groupBy("a", "c").agg(F.sum(pair_cost(F.col("hit") + F.col("h2"), F.col("pairs") + F.col("p2") - F.col("hit") - F.col("h2"))).alias("outer"))
    met = between.join(F.broadcast(now), "a").join(F.broadcast(now.select(F.col("a").alias("c"), F.col("cost").alias("cost2"))), "c").join(F.broadcast(inner), "a").join(F.broadcast(inner.select(F.col("a").alias("c"), F.col("p").alias("p2"), F.col("h").alias("h2"))), "c").join(merged, ["a", "c"], "left")
    hit, pairs = F.col("h") + F.col("h2") + F.col("hx"), F.col("p") + F.col("p2") + F.col("px")
    after = F.coalesce("outer", F.lit(0.0)) + pair_cost(hit, pairs - hit)
    return met.select("a", "c", (after - (F.col("cost") + F.col("cost2") - F.col("cx"))).alias("change"))


def merge_small(edges: DataFrame, labels: DataFrame, n_blocks: int, min_block: int) -> DataFrame:
    """One repair step: the smallest non-empty block below min_block joins the partner that costs least."""
    stats = block_pairs(edges, labels, n_blocks)
    small = block_sizes(labels, n_blocks).where((F.col("n") > 0) & (F.col("n") < min_block)).orderBy("n", "a").limit(1).select("a")
    full = block_sizes(labels, n_blocks, "c").where("n > 0").select("c")
    best = merge_cost(stats).join(F.broadcast(small), "a").join(F.broadcast(full), "c").groupBy("a").agg(F.min_by("c", F.struct(F.round("change", 9), "c")).alias("into"))
    return labels.join(F.broadcast(best), labels["lab"] == best["a"], "left").select("id", F.coalesce("into", "lab").cast("int").alias("lab"))


def merge_until(edges: DataFrame, labels: DataFrame, n_blocks: int, min_block: int) -> DataFrame:
    """merge_small until every block has min_block members."""
    for _ in range(n_blocks):
        if labels.groupBy("lab").agg(F.count("*").alias("n")).where(F.col("n") < min_block).isEmpty():
            break
        labels = write_state(merge_small(edges, labels, n_blocks, min_block), "merged")
    return labels


def relabel(edges: DataFrame, seed: int) -> DataFrame:
    """Naive anonymisation: ids replaced by ranks of a hash; shape and degrees stay as they are."""
    ids = vertices(edges).select("id", portable(seed, "relabel", F.col("id")).alias("u"))
    ranks = member_ranks_by(ids)
    one = edges.select("src", "dst").join(ranks.select(F.col("id").alias("src"), F.col("rank").alias("x")), "src").join(ranks.select(F.col("id").alias("dst"), F.col("rank").alias("y")), "dst")
    return one.select(F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst"))


def member_ranks_by(ids: DataFrame, ranges: int = 256) -> DataFrame:
    """id, rank by (u, id), through ranges of u."""
    rows = ids.withColumn("part", F.floor(F.col("u") * ranges).cast("int"))
    before = rows.groupBy("part").agg(F.count("*").alias("n")).withColumn("before", F.coalesce(F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    return rows.join(F.broadcast(before), "part").select("id", (F.row_number().over(W.partitionBy("part").orderBy("u", "id")) - 1 + F.col("before")).alias("rank"))


def annealed_partition(edges: DataFrame, n_blocks: int, min_block: int, seed: int = 1, steps: int = 2000) -> DataFrame:
    """id, lab by annealed single moves under a size floor: a labelled stand-in for an earlier clustering anonymiser.

    Serial, in one task; for small graphs.
    """
    import pandas as pd

    from ..hard import kernel

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        ids = np.unique(frame[["src", "dst"]].to_numpy())
        graph = kernel.Graph(len(ids), np.searchsorted(ids, frame["src"]), np.searchsorted(ids, frame["dst"]))
        rng = np.random.default_rng(seed)
        lab = np.arange(len(ids)) % n_blocks
        rng.shuffle(lab)
        now = graph.entropy(lab, n_blocks)
        for step in range(steps):
            v, a = int(rng.integers(len(ids))), int(rng.integers(n_blocks))
            old = lab[v]
            if a == old or (lab == old).sum() <= min_block:
                continue
            lab[v] = a
            after = graph.entropy(lab, n_blocks)
            if after < now or rng.random() < np.exp((now - after) / max(1e-9, 5.0 * (1 - step / steps))):
                now = after
            else:
                lab[v] = old
        return pd.DataFrame({"id": ids, "lab": lab.astype(np.int32)})

    return edges.select("src", "dst", F.lit(0).alias("one")).groupBy("one").applyInPandas(run, "id long, lab int")
