"""Rounds of a simple graph from packed rows: the neighbours of all vertices are written once, as positions, and each task
reads the packs it decides or counts.

A task holds one pack and a label a vertex, the driver an id and a label a vertex; edges stay in the shared folder.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..em.loop import Stop, Trace
from ..graph import both_ways
from ..plans.state import write_state
from ..rng import portable_numpy
from . import kernel

ENDS = 1 << 20
READ = "16m"


class Pack(kernel.Graph):
    """Some vertices of a graph by number in the pack, with the positions of all their neighbours."""

    def __init__(self, vertices: np.ndarray, lengths: np.ndarray, other: np.ndarray) -> None:
        self.n, self.vertices, self.other = len(vertices), vertices, other
        self.start = np.concatenate(([0], np.cumsum(lengths, dtype=np.int64)))

    def named(self, chosen: np.ndarray) -> np.ndarray:
        return self.vertices[chosen]

    def hits(self, lab: np.ndarray, k: int) -> np.ndarray:
        """Links from block to block, seen from the vertices of the pack."""
        own, out = np.repeat(lab[self.vertices], np.diff(self.start)), np.zeros(k * k, np.int64)
        for at in range(0, len(own), kernel.EDGES):
            s = slice(at, at + kernel.EDGES)
            out += np.bincount(own[s].astype(np.int64) * k + lab[self.other[s]], minlength=k * k)
        return out


def _packing(known):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = known.value
        held = [tuple(np.searchsorted(ids, c.to_numpy()).astype(np.int32) for c in batch.columns) for batch in batches]
        if held:
            own, other = (np.concatenate(c) for c in zip(*held))
            held.clear()
            order = np.argsort(own, kind="stable")
            own, other = own[order], other[order]
            vertices = np.unique(own)
            linked = own != other  # each vertex has a row with itself, so that it is there without links
            lengths = np.bincount(np.searchsorted(vertices, own[linked]), minlength=len(vertices)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in (vertices, lengths, other[linked])], ["vertices", "lengths", "others"])

    return run


def _each_pack(work: Callable[[Pack], pa.RecordBatch]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                yield work(Pack(*(np.frombuffer(c[row].as_buffer(), np.int32) for c in batch.columns)))

    return run


@contextmanager
def _few_packs_a_task(spark: SparkSession) -> Iterator[None]:
    """Reads are planned by READ: a task's packs travel to its worker in one batch."""
    key = "spark.sql.files.maxPartitionBytes"
    before = spark.conf.get(key)
    spark.conf.set(key, READ)
    try:
        yield
    finally:
        spark.conf.set(key, before)


def fit_packed(edges: DataFrame, labels: DataFrame, k: int, share: Callable[[int], float], seed: int, stop: Stop, min_block: int = 0, damping: float = 0.0) -> tuple[DataFrame, Trace]:
    """Labels and trace of sampled reassignment with table scores: the moves of kernel.rounds. edges and labels are best written."""
    context = edges.sparkSession.sparkContext
    edges, trace = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")), Trace("hard")
    start = labels.select(F.col("id").cast("long").alias("id"), F.col("lab").cast("int").alias("lab")).toArrow()
    order = np.argsort(start.column("id").to_numpy(), kind="stable")
    ids, lab = (start.column(c).to_numpy()[order] for c in ("id", "lab"))
    known = context.broadcast(ids)
    own = labels.select(F.col("id").cast("long").alias("id"), F.col("id").cast("long").alias("other"))
    rows = both_ways(edges).unionAll(own)
    packs = write_state(rows.repartition(max(1, math.ceil(2 * edges.count() / ENDS)), "id").mapInArrow(_packing(known), "vertices binary, lengths binary, others binary"), "packs")

    def counts() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        sent = context.broadcast(lab)
        count = lambda pack: pa.RecordBatch.from_arrays([pa.array([pack.hits(sent.value, k).tobytes()], pa.binary())], ["hits"])
        hit = np.zeros((k, k))
        with _few_packs_a_task(edges.sparkSession):
            for row in packs.mapInArrow(_each_pack(count), "hits binary").collect():
                hit += np.frombuffer(row["hits"], np.int64).reshape(k, k)
        sent.unpersist()
        hit[np.arange(k), np.arange(k)] /= 2
        size = np.bincount(lab, minlength=k).astype(float)
        return size, hit, kernel.misses(size, hit)

    def moves(number: int, now: tuple) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        sent, frac = context.broadcast((lab, now)), share(number)

        def decide(pack: Pack) -> pa.RecordBatch:
            (own, tables), names = sent.value, known.value[pack.vertices]
            chosen = np.flatnonzero(portable_numpy(seed, "choose", number, names) < frac) if frac < 1 else np.arange(pack.n)
            best, gain = kernel.decided(pack, own, k, chosen, tables)
            go = best != own[pack.vertices[chosen]]
            if damping:
                go[go] = portable_numpy(seed, "damp", number, names[chosen[go]]) >= damping
            return pa.RecordBatch.from_arrays([pa.array(pack.vertices[chosen[go]]), pa.array(best[go].astype(np.int32)), pa.array(gain[go])], ["at", "lab", "gain"])

        with _few_packs_a_task(edges.sparkSession):
            found = packs.mapInArrow(_each_pack(decide), "at int, lab int, gain double").toArrow()
        sent.unpersist()
        return tuple(found.column(c).to_numpy() for c in ("at", "lab", "gain"))

    now = counts()
    trace.add(kernel.entropy_of(*now[1:]))
    while not stop.reached(trace.entropies, trace.elapsed()):
        at, to, gain = moves(len(trace.rows), now)
        if min_block:
            leave = kernel.allowed_to_leave(gain, lab[at], ids[at], np.bincount(lab, minlength=k), min_block)
            at, to = at[leave], to[leave]
        if len(at):
            lab = lab.copy()
            lab[at] = to
            now = counts()
        trace.add(kernel.entropy_of(*now[1:]), len(at))
    last = context.broadcast(lab)
    named = lambda pack: pa.RecordBatch.from_arrays([pa.array(known.value[pack.vertices]), pa.array(last.value[pack.vertices])], ["id", "lab"])
    return packs.mapInArrow(_each_pack(named), "id long, lab int"), trace
