"""Sampled reassignment: each round re-decides a random share of the items against frozen statistics."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..em.loop import Stop, Trace
from ..graph import vertices
from ..init import random_labels
from ..plans.state import drop_state, write_state
from ..rng import portable
from . import kernel
from .packed import fit_packed
from .problems import ObservedWeights, Problem, SimpleGraph, State
from .score import score_exact
from .stats import block_pairs, block_sizes, simple_entropy, vertex_links

Frac = float | Callable[[int], float]


@dataclass
class HardFit:
    labels: DataFrame
    trace: Trace
    right: DataFrame | None = None


def share(frac: Frac, round_: int) -> float:
    return frac(round_) if callable(frac) else frac


def picked(frac: float, seed: int, round_: int, side: str = ""):
    """The choice of a round, as a condition on id: a hash of (seed, round, id) below frac."""
    return F.lit(True) if frac >= 1 else portable(seed, f"choose{side}", round_, F.col("id")) < frac


def choose(labels: DataFrame, frac: float, seed: int, round_: int, side: str = "") -> DataFrame:
    return labels.where(picked(frac, seed, round_, side))


def keep_min_size(moves: DataFrame, labels: DataFrame, n_blocks: int, min_block: int) -> DataFrame:
    """Refuse departures that would bring a block below min_block: the best gains of each block leave, by rank.

    Ranks in two steps, by ranges of gains first, so that no task sorts all that would leave a large block.
    """
    leaving = moves.where("lab <> y").withColumn("part", F.floor(-8 * F.ln(F.greatest("gain", F.lit(1e-300)))).cast("int"))
    counts = leaving.groupBy("y", "part").agg(F.count("*").alias("n"))
    before = counts.select("y", "part", F.coalesce(F.sum("n").over(W.partitionBy("y").orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    inside = F.row_number().over(W.partitionBy("y", "part").orderBy(F.desc("gain"), "id"))
    ranked = leaving.withColumn("inside", inside).join(before, ["y", "part"])
    sizes = block_sizes(labels, n_blocks, "y")
    return ranked.join(F.broadcast(sizes), "y").where(F.col("inside") + F.col("before") <= F.greatest(F.lit(0), F.col("n") - min_block)).select("id", "lab")


def plan_moves(problem: Problem, state: State, side: str, frac: float, seed: int, round_: int, statistics: DataFrame, min_block: int = 0, damping: float = 0.0) -> DataFrame:
    """id, lab of the items of a side that move in a round. damping: the share of moves that are held back."""
    labels = state[side].select("id", "lab")
    moves = problem.moves(state, side, choose(labels, frac, seed, round_, side), picked(frac, seed, round_, side), statistics)
    if damping:
        moves = moves.where(portable(seed, f"damp{side}", round_, F.col("id")) >= damping)
    return keep_min_size(moves, labels, problem.sides[side], min_block) if min_block else moves.select("id", "lab")


def apply_moves(labels: DataFrame, moves: DataFrame) -> DataFrame:
    """labels with was, the label before."""
    return labels.select("id", "lab").join(moves.select("id", F.col("lab").alias("new")), "id", "left").select("id", F.coalesce("new", "lab").alias("lab"), F.col("lab").alias("was"))


def sampled_reassign(problem: Problem, state: State, frac: Frac = 0.1, seed: int = 1, stop: Stop | None = None, min_block: int = 0, damping: float = 0.0, run_id: str = "hard") -> tuple[State, Trace]:
    """Any problem: choose a share of the items of each side, score every block for each against frozen statistics, plan
    the moves, apply them all, refresh the statistics. Returns the last state and the trace."""
    stop, trace = stop or Stop(max_iter=30), Trace(run_id)
    state = {side: write_state(labels.select("id", "lab"), "labels") for side, labels in state.items()}
    statistics = write_state(problem.statistics(state), "statistics")
    trace.add(problem.entropy(statistics))
    while not stop.reached(trace.entropies, trace.elapsed()):
        number, moved = len(trace.rows), 0
        for side in problem.sides:
            moves = plan_moves(problem, state, side, share(frac, number), seed, number, statistics, min_block, damping)
            after = write_state(apply_moves(state[side], moves), "labels")
            moved += after.where("lab <> was").count()
            drop_state(state[side])
            drop_state(statistics)
            state = state | {side: after}
            statistics = write_state(problem.statistics({s: x.select("id", "lab") for s, x in state.items()}), "statistics")
        trace.add(problem.entropy(statistics), moved)
    return {side: labels.select("id", "lab") for side, labels in state.items()}, trace


def one_round(edges: DataFrame, labels: DataFrame, n_blocks: int, frac: float, scorer: str, seed: int, round_: int, min_block: int = 0) -> DataFrame:
    """labels with was, the label before, after one round on a simple graph."""
    problem, state = SimpleGraph(edges, n_blocks, scorer), {"": labels}
    statistics = write_state(problem.statistics(state), "statistics")  # scores read them several times
    return apply_moves(labels, plan_moves(problem, state, "", frac, seed, round_, statistics, min_block))


def entropy_of(edges: DataFrame, labels: DataFrame, n_blocks: int) -> float:
    return simple_entropy(block_pairs(edges, labels, n_blocks)).first()[0]


def fit_simple(edges: DataFrame, n_blocks: int, frac: Frac = 0.1, scorer: str = "arrow", seed: int = 1, stop: Stop | None = None, start: DataFrame | None = None, ids: DataFrame | None = None, min_block: int = 0, backend: str = "frames", damping: float = 0.0) -> HardFit:
    """Cluster a simple graph. backend: frames (any size), packed (packed neighbours in the shared folder, a label a vertex
    in each task and on the driver), or task, all rounds in one task, for a graph that fits one (both: table scores only);
    the caller says which. All make the same moves, read frac every round and stop alike."""
    stop = stop or Stop(max_iter=30)
    edges = edges.select("src", "dst")
    labels = start or random_labels(ids or vertices(edges), n_blocks, seed)
    if backend == "task":
        if scorer not in ("table", "arrow"):
            raise ValueError("the one-task backend has table scores only")
        return fit_in_task(edges, labels, n_blocks, frac, seed, stop, min_block, damping)
    if backend == "packed":
        if scorer not in ("table", "arrow"):
            raise ValueError("the packed backend has table scores only")
        return HardFit(*fit_packed(edges, write_state(labels, "labels"), n_blocks, lambda number: share(frac, number), seed, stop, min_block, damping))
    if backend != "frames":
        raise ValueError(f"no backend {backend}")
    state, trace = sampled_reassign(SimpleGraph(edges, n_blocks, scorer), {"": labels}, frac, seed, stop, min_block, damping)
    return HardFit(state[""], trace)


def _run_in_task(n_blocks: int, fracs: list[float], seed: int, stop: Stop, min_block: int, damping: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        kind, a, b = (table.column(c).to_numpy() for c in ("kind", "a", "b"))
        order = np.argsort(a[kind == 0], kind="stable")
        ids, lab = a[kind == 0][order], b[kind == 0][order]
        graph = kernel.Graph(len(ids), np.searchsorted(ids, a[kind == 1]), np.searchsorted(ids, b[kind == 1]))
        began = time.monotonic()
        rows = [(graph.entropy(lab, n_blocks), 0, 0.0)]
        for lab, entropy, moved in kernel.rounds(graph, lab, n_blocks, fracs, stop.max_iter, seed, ids, stop, min_block, damping):
            rows.append((entropy, moved, time.monotonic() - began))
        n = len(ids)
        yield pa.RecordBatch.from_arrays(
            [
                pa.array(np.concatenate((np.zeros(n, np.int64), np.ones(len(rows), np.int64)))),
                pa.array(np.concatenate((ids, np.arange(len(rows))))),
                pa.array(np.concatenate((lab, [m for _, m, _ in rows])).astype(np.int64)),
                pa.array(np.concatenate((np.zeros(n), [e for e, _, _ in rows]))),
                pa.array(np.concatenate((np.zeros(n), [s for _, _, s in rows]))),
            ],
            ["kind", "a", "b", "value", "seconds"],
        )

    return run


def fit_in_task(edges: DataFrame, labels: DataFrame, n_blocks: int, frac: Frac, seed: int, stop: Stop, min_block: int = 0, damping: float = 0.0) -> HardFit:
    """All rounds in one task, which holds the graph; the trace has the seconds that the task measured."""
    sent = labels.select(F.lit(0).cast("long").alias("kind"), F.col("id").alias("a"), F.col("lab").cast("long").alias("b")).unionAll(edges.select(F.lit(1).cast("long"), "src", "dst"))
    fracs = [share(frac, number) for number in range(1, stop.max_iter + 1)]
    ran = write_state(sent.coalesce(1).mapInArrow(_run_in_task(n_blocks, fracs, seed, stop, min_block, damping), "kind long, a long, b long, value double, seconds double"), "task")
    trace = Trace("hard")
    trace.rows = [("hard", r["a"], r["seconds"], r["value"], r["b"]) for r in ran.where("kind = 1").orderBy("a").collect()]
    return HardFit(ran.where("kind = 0").select(F.col("a").alias("id"), F.col("b").cast("int").alias("lab")), trace)


def local_optimality(edges: DataFrame, labels: DataFrame, n_blocks: int) -> DataFrame:
    """gain and locally_optimal: by how much the best single move lowers the entropy, and whether none does."""
    scores = score_exact(vertex_links(edges, labels), labels, block_pairs(edges, labels, n_blocks))
    stay = F.max(F.when(F.col("a") == F.col("y"), F.col("score")))
    per = scores.groupBy("id").agg((stay - F.min("score")).alias("gain"))
    return per.agg(F.max("gain").alias("gain")).withColumn("locally_optimal", F.col("gain") <= 1e-9)


def polish(edges: DataFrame, labels: DataFrame, n_blocks: int) -> tuple[DataFrame, int]:
    """Labels that no single move improves, and how many moves that took, with all tables distributed.

    Each turn takes the exact gains of all moves, applies the best of each vertex for the best `batch` vertices and keeps
    the result if the entropy falls by more than a margin; else it tries half as many, down to one, which always falls.
    """
    labels, total, batch = write_state(labels.select("id", "lab"), "labels"), 0, None
    while True:
        statistics = write_state(block_pairs(edges, labels, n_blocks), "statistics")
        now = simple_entropy(statistics).first()[0]
        scores = score_exact(vertex_links(edges, labels), labels, statistics, n_blocks)
        stay = F.max(F.when(F.col("a") == F.col("y"), F.col("score")))
        best = scores.groupBy("id").agg((stay - F.min("score")).alias("gain"), F.min_by("a", F.struct(F.round("score", 9), "a")).alias("lab")).where("gain > 1e-9")
        best = write_state(best, "moves")
        drop_state(statistics)
        many = best.count()
        if not many:
            return labels, total
        batch = min(many, batch or many)
        while True:
            moves = best.orderBy(F.desc(F.round("gain", 9)), "id").limit(batch)
            after = write_state(apply_moves(labels, moves).select("id", "lab"), "labels")
            if batch == 1 or entropy_of(edges, after, n_blocks) < now - 1e-9:
                break
            drop_state(after)
            batch = max(1, batch // 2)
        drop_state(labels)
        drop_state(best)
        labels, total, batch = after, total + batch, batch * 2


def turned(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "cat")


def rating_round(edges: DataFrame, own: DataFrame, other: DataFrame, frac: float, seed: int, round_: int, side: str) -> DataFrame:
    """labels of the own side (id, lab, was) after one round; edges(src, dst, cat): src is the own side."""
    problem = ObservedWeights.ratings(edges if side == "l" else turned(edges), 1, 1)
    state = {side: own, "r" if side == "l" else "l": other}
    return apply_moves(own, plan_moves(problem, state, side, frac, seed, round_, problem.statistics(state)))


def fit_sides(problem: Problem, left: DataFrame, right: DataFrame, frac: Frac = 0.1, seed: int = 1, stop: Stop | None = None, min_block: int = 0, damping: float = 0.0, run_id: str = "hard") -> HardFit:
    """Any two-sided problem from given labels."""
    state, trace = sampled_reassign(problem, {"l": left, "r": right}, frac, seed, stop or Stop(max_iter=10), min_block, damping, run_id)
    return HardFit(state["l"], trace, state["r"])


def side_labels(edges: DataFrame, left_blocks: int, right_blocks: int, seed: int) -> tuple[DataFrame, DataFrame]:
    return random_labels(edges.select(F.col("src").alias("id")).distinct(), left_blocks, seed), random_labels(edges.select(F.col("dst").alias("id")).distinct(), right_blocks, seed + 1)


def fit_rating(edges: DataFrame, left_blocks: int, right_blocks: int, frac: Frac = 0.1, seed: int = 1, stop: Stop | None = None) -> HardFit:
    """Hard clustering of both sides of a rating graph edges(src, dst, cat), one side after the other."""
    return fit_sides(ObservedWeights.ratings(edges, left_blocks, right_blocks), *side_labels(edges, left_blocks, right_blocks, seed), frac, seed, stop, run_id="rating")


def fit_binomial(edges: DataFrame, left_blocks: int, right_blocks: int, frac: Frac = 0.1, seed: int = 1, stop: Stop | None = None) -> HardFit:
    """The same for edges(src, dst, w, trials): w successes of `trials` on each observed edge."""
    return fit_sides(ObservedWeights.binomial(edges, left_blocks, right_blocks), *side_labels(edges, left_blocks, right_blocks, seed), frac, seed, stop, run_id="binomial")


def fit_bipartite(edges: DataFrame, left_blocks: int, right_blocks: int, frac: Frac = 0.1, seed: int = 1, stop: Stop | None = None) -> HardFit:
    """The same for edges(src, dst) among all pairs of both sides."""
    from .problems import BipartiteGraph

    problem = BipartiteGraph(edges.select("src", "dst"), left_blocks, right_blocks)
    return fit_sides(problem, *side_labels(edges, left_blocks, right_blocks, seed), frac, seed, stop, run_id="bipartite")


def fit_directed(edges: DataFrame, n_blocks: int, frac: Frac = 0.1, seed: int = 1, stop: Stop | None = None, min_block: int = 0) -> HardFit:
    """Cluster a directed graph edges(src, dst); loops don't count."""
    from .problems import DirectedGraph

    own = edges.where("src <> dst").select("src", "dst")
    state, trace = sampled_reassign(DirectedGraph(own, n_blocks), {"": random_labels(vertices(edges), n_blocks, seed)}, frac, seed, stop, min_block, run_id="directed")
    return HardFit(state[""], trace)
