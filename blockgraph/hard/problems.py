"""What sampled reassignment needs to know of a graph family: statistics of a labeling, their entropy, and moves.

A state holds the labels of each side, (id, lab). Statistics have a row a block pair (or a cell of one) and are written
once a turn; scores read them and the links of the chosen items only.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graph import both_ways
from ..plans.placement import BROADCAST_BYTES, pairs_table
from . import kernel
from .score import SCORERS, best_moves, score_rows
from .stats import block_pairs, block_sizes, c_log, cost_rows, labelled, pair_cost, simple_entropy, turned_pairs, xlogx

State = dict[str, DataFrame]


class Problem(Protocol):
    """sides: the labelled sides, re-decided one after the other, with their numbers of blocks."""

    sides: dict[str, int]

    def statistics(self, state: State) -> DataFrame: ...

    def entropy(self, statistics: DataFrame) -> float: ...

    def moves(self, state: State, side: str, chosen: DataFrame, picked: Column, statistics: DataFrame) -> DataFrame:
        """id, lab, gain, y of the chosen items (id, lab); picked is the same choice as a condition on id."""
        ...


def links_of(edges: DataFrame, own: str, other: str, picked: Column, labels: DataFrame, *more: str) -> DataFrame:
    """id, b and `more` of the edges of chosen items: the choice is a condition on the edge, before any join."""
    ends = edges.select(F.col(own).alias("id"), F.col(other).alias("other"), *more).where(picked)
    return ends.join(labels.select(F.col("id").alias("other"), F.col("lab").alias("b")), "other")


def counted(ends: DataFrame) -> DataFrame:
    return ends.groupBy("id", "b").agg(F.count("*").alias("x"))


@dataclass(frozen=True)
class SimpleGraph:
    """Undirected simple graph. scorer: table, plugin or exact (expressions), or arrow, the table scores in numpy batches
    against statistics of at most BROADCAST_BYTES (beyond that: table)."""

    edges: DataFrame
    n_blocks: int
    scorer: str = "table"

    @property
    def sides(self) -> dict[str, int]:
        return {"": self.n_blocks}

    def statistics(self, state: State) -> DataFrame:
        return block_pairs(self.edges, state[""], self.n_blocks)

    def entropy(self, statistics: DataFrame) -> float:
        return simple_entropy(statistics).first()[0]

    def moves(self, state: State, side: str, chosen: DataFrame, picked: Column, statistics: DataFrame) -> DataFrame:
        links = counted(links_of(both_ways(self.edges).withColumnsRenamed({"id": "src", "other": "dst"}), "src", "dst", picked, state[""]))
        if self.scorer == "arrow" and 16 * self.n_blocks**2 <= BROADCAST_BYTES:
            return arrow_moves(links, chosen, statistics, self.n_blocks)
        return best_moves(SCORERS["table" if self.scorer == "arrow" else self.scorer](links, chosen, statistics, self.n_blocks))


def arrow_moves(links: DataFrame, chosen: DataFrame, statistics: DataFrame, k: int) -> DataFrame:
    """best_moves of table scores, a batch of items at a time: one row an item instead of one an item and block."""
    found = statistics.select("a", "b", "hit", "miss", "na").toArrow()  # k * (k + 1) / 2 rows; the caller has checked k
    a, b = found.column("a").to_numpy(), found.column("b").to_numpy()
    hit, miss, size = np.zeros((k, k)), np.zeros((k, k)), np.zeros(k)
    for matrix, name in ((hit, "hit"), (miss, "miss")):
        matrix[a, b] = matrix[b, a] = found.column(name).to_numpy()
    size[a] = found.column("na").to_numpy()
    shared = links.sparkSession.sparkContext.broadcast((size, hit, miss))

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size, hit, miss = shared.value
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            own = batch.column(1).to_numpy().astype(np.int64)
            touched = batch.column(2)
            row = np.repeat(np.arange(n), np.diff(touched.offsets.to_numpy()))
            cells = touched.flatten()
            blocks, x = cells.field("b").to_numpy().astype(np.int64), cells.field("x").to_numpy().astype(float)
            cell, where = np.unique(np.concatenate((row * k + blocks, np.arange(n) * k + own)), return_inverse=True)
            x = np.bincount(where, np.concatenate((x, np.zeros(n))))
            best, gain = kernel.best_blocks(kernel.scores_of(size, hit, miss, cell // k, cell % k, x, own), own)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(best.astype(np.int32)), pa.array(gain), batch.column(1)], ["id", "lab", "gain", "y"])

    per = links.groupBy("id").agg(F.collect_list(F.struct("b", F.col("x").cast("double").alias("x"))).alias("t"))
    none = F.array().cast("array<struct<b:int,x:double>>")
    rows = chosen.join(per, "id", "left").select(F.col("id").cast("long").alias("id"), F.col("lab").cast("int").alias("y"), F.coalesce("t", none).alias("t"))
    return rows.mapInArrow(decide, "id long, lab int, gain double, y int")


@dataclass(frozen=True)
class DirectedGraph:
    """Directed simple graph without loops; links out and links in are scored apart, each against frozen counts."""

    edges: DataFrame
    n_blocks: int

    @property
    def sides(self) -> dict[str, int]:
        return {"": self.n_blocks}

    def statistics(self, state: State) -> DataFrame:
        return block_pairs(self.edges, state[""], self.n_blocks, directed=True)

    def entropy(self, statistics: DataFrame) -> float:
        return simple_entropy(statistics).first()[0]

    def moves(self, state: State, side: str, chosen: DataFrame, picked: Column, statistics: DataFrame) -> DataFrame:
        parts = []
        for own, other, rows in (("src", "dst", statistics), ("dst", "src", turned_pairs(statistics))):
            links = counted(links_of(self.edges, own, other, picked, state[""]))
            parts.append(score_rows(links, chosen, cost_rows(rows, True), True, self.n_blocks))
        return best_moves(parts[0].unionAll(parts[1]).groupBy("id", "y", "a").agg(F.sum("score").alias("score")))


@dataclass(frozen=True)
class BipartiteGraph:
    """Bipartite graph in which all pairs of both sides are possible, observed or not."""

    edges: DataFrame
    left_blocks: int
    right_blocks: int

    @property
    def sides(self) -> dict[str, int]:
        return {"l": self.left_blocks, "r": self.right_blocks}

    def statistics(self, state: State) -> DataFrame:
        return block_pairs(self.edges, state["l"], self.left_blocks, state["r"], self.right_blocks)

    def entropy(self, statistics: DataFrame) -> float:
        return simple_entropy(statistics).first()[0]

    def moves(self, state: State, side: str, chosen: DataFrame, picked: Column, statistics: DataFrame) -> DataFrame:
        own, other, rows, there = ("src", "dst", statistics, "r") if side == "l" else ("dst", "src", turned_pairs(statistics), "l")
        links = counted(links_of(self.edges, own, other, picked, state[there]))
        return best_moves(score_rows(links, chosen, cost_rows(rows, False), False, max(self.left_blocks, self.right_blocks)))


@dataclass(frozen=True)
class ObservedWeights:
    """Bipartite graph of which only the observed pairs count, each with amounts of some categories.

    amounts(src, dst, k, x): one row a category with x > 0. Ratings: k the rating, x = 1. Binomial weights: k 0 and 1, x
    the successes and the failures of an edge's trials. Entropy and moves are exact for each item alone.
    """

    amounts: DataFrame
    left_blocks: int
    right_blocks: int

    @classmethod
    def ratings(cls, edges: DataFrame, left_blocks: int, right_blocks: int) -> ObservedWeights:
        return cls(edges.select("src", "dst", F.col("cat").alias("k"), F.lit(1.0).alias("x")), left_blocks, right_blocks)

    @classmethod
    def binomial(cls, edges: DataFrame, left_blocks: int, right_blocks: int) -> ObservedWeights:
        both = F.array(F.struct(F.lit(0).alias("k"), F.col("w").cast("double").alias("x")), F.struct(F.lit(1).alias("k"), (F.col("trials") - F.col("w")).cast("double").alias("x")))
        return cls(edges.select("src", "dst", F.inline(both)).where("x > 0"), left_blocks, right_blocks)

    @property
    def sides(self) -> dict[str, int]:
        return {"l": self.left_blocks, "r": self.right_blocks}

    def statistics(self, state: State) -> DataFrame:
        """a, b, k, n: amounts by cell."""
        return labelled(self.amounts, state["l"], state["r"]).groupBy("a", "b", "k").agg(F.sum("x").alias("n"))

    def entropy(self, statistics: DataFrame) -> float:
        pairs = statistics.groupBy("a", "b").agg((xlogx(F.sum("n")) - F.sum(xlogx(F.col("n")))).alias("e"))
        return pairs.agg(F.sum("e")).first()[0] or 0.0

    def moves(self, state: State, side: str, chosen: DataFrame, picked: Column, statistics: DataFrame) -> DataFrame:
        own, other, there = ("src", "dst", "r") if side == "l" else ("dst", "src", "l")
        cells = statistics if side == "l" else statistics.select(F.col("b").alias("a"), F.col("a").alias("b"), "k", "n")
        links = links_of(self.amounts, own, other, picked, state[there], "k", "x").groupBy("id", "b", "k").agg(F.sum("x").alias("x"))
        return best_moves(self.scores(links, chosen, state[side], cells))

    def scores(self, links: DataFrame, chosen: DataFrame, labels: DataFrame, cells: DataFrame) -> DataFrame:
        """id, y, a, score: exact change of the entropy when an item joins block a after leaving its own; links, chosen:
        of the chosen items; cells(a, b, k, n): a is a block of the items' side."""
        k = max(self.left_blocks, self.right_blocks)
        pairs = cells.groupBy("a", "b").agg(F.sum("n").alias("n"))
        placed = links.join(chosen.select("id", F.col("lab").alias("y")), "id")
        sums = placed.groupBy("id", "y", "b").agg(F.sum("x").alias("x"))
        blocks = F.broadcast(labels.select(F.col("lab").alias("a")).distinct().agg(F.collect_list("a").alias("all_a")))  # one row

        def change(found: DataFrame, counts: DataFrame, keys: list[str], sign: int) -> DataFrame:
            met = found.join(blocks).withColumn("a", F.explode("all_a")).drop("all_a").join(pairs_table(counts, k), ["a", *keys], "left")
            base = F.coalesce("n", F.lit(0.0)) - F.when(F.col("a") == F.col("y"), F.col("x")).otherwise(0.0)
            return met.select("id", "y", "a", (sign * (xlogx(base + F.col("x"), c_log) - xlogx(base, c_log))).alias("part"))

        parts = change(sums, pairs, ["b"], 1).unionAll(change(placed, cells, ["b", "k"], -1))
        return parts.groupBy("id", "y", "a").agg(F.sum("part").alias("score"))


def ordered_entropy(edges: DataFrame, labels: DataFrame, n_blocks: int) -> DataFrame:
    """Entropy of a directed labeling, as a table."""
    return block_pairs(edges, labels, n_blocks, directed=True).agg(F.sum(pair_cost(F.col("hit"), F.col("miss"))).alias("entropy"))


__all__ = ["BipartiteGraph", "DirectedGraph", "ObservedWeights", "Problem", "SimpleGraph", "arrow_moves", "block_sizes", "links_of", "ordered_entropy"]
