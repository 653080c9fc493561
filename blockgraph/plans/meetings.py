"""Pairs of members that share groups, block by block of members: memberships move, pairs never do."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

AT_ONCE = 1_000_000
SENT = 1 << 16
ROWS = "cell int, kind int, x long, y long"


def _cells(members: DataFrame, edges: DataFrame | None, blocks: int) -> DataFrame:
    """Rows of ROWS: memberships (kind 0 of the cell's row, 1 of its column; x the member, y the group) and edges (2)."""
    block = lambda c: F.pmod(F.xxhash64(F.col(c)), F.lit(blocks)).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    dealt = members.select(block("member").alias("own"), other.alias("other"), F.col("member").alias("x"), F.col("grp").alias("y"))
    own, low, high = F.col("own"), F.least("own", "other"), F.greatest("own", "other")
    rows = dealt.select((low * blocks + high).alias("cell"), F.when(own == low, 0).otherwise(1).alias("kind"), "x", "y")
    if edges is not None:
        ends = edges.select(block("src").alias("s"), block("dst").alias("d"), "src", "dst")
        turned = F.col("s") > F.col("d")
        rows = rows.unionAll(ends.select((F.least("s", "d") * blocks + F.greatest("s", "d")).alias("cell"), F.lit(2).alias("kind"), F.when(turned, F.col("dst")).otherwise(F.col("src")).alias("x"), F.when(turned, F.col("src")).otherwise(F.col("dst")).alias("y")))
    return rows


def _met(own: np.ndarray, theirs: np.ndarray, same: bool) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """For each member of the row: the member, all members of the column in order, and how many groups it shares with each.
    In a cell of one block with itself only later members count."""
    right, place = np.unique(theirs[0], return_inverse=True)
    order = np.argsort(theirs[1], kind="stable")
    groups, start = np.unique(theirs[1][order], return_index=True)
    lists = np.split(place[order], start[1:]) if len(groups) else []
    order = np.argsort(own[0], kind="stable")
    left, start = np.unique(own[0][order], return_index=True)
    for member, its in zip(left, np.split(own[1][order], start[1:]) if len(left) else []):
        at = np.searchsorted(groups, its)
        known = [lists[k] for k, g in zip(at, its) if k < len(groups) and groups[k] == g]
        shared = np.bincount(np.concatenate(known), minlength=len(right)) if known else np.zeros(len(right), np.int64)
        if same:
            shared[: np.searchsorted(right, member, "right")] = 0
        yield member, right, shared


def _pairs(parts: list[np.ndarray], same: bool) -> Iterator[list[np.ndarray]]:
    held, many = [], 0
    for member, right, shared in _met(parts[0], parts[0] if same else parts[1], same):
        at = np.flatnonzero(shared)
        held.append((np.minimum(right[at], member), np.maximum(right[at], member), shared[at]))
        many += len(at)
        if many >= SENT:
            yield [np.concatenate(c) for c in zip(*held)]
            held, many = [], 0
    if many:
        yield [np.concatenate(c) for c in zip(*held)]


def _counts(parts: list[np.ndarray], same: bool) -> Iterator[list[np.ndarray]]:
    pairs = hits = 0
    order = np.argsort(parts[2][0], kind="stable")
    x, y = parts[2][0][order], parts[2][1][order]
    for member, right, shared in _met(parts[0], parts[0] if same else parts[1], same):
        pairs += np.count_nonzero(shared)
        mine = y[np.searchsorted(x, member) : np.searchsorted(x, member, "right")]
        if len(mine) and len(right):
            at = np.minimum(np.searchsorted(right, mine), len(right) - 1)
            hits += np.count_nonzero((right[at] == mine) & (shared[at] > 0))
    yield [np.array([pairs]), np.array([hits])]


def _by_cell(blocks: int, work: Callable, names: tuple[str, ...]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def done(cell: int, held: list) -> Iterator[pa.RecordBatch]:
            kind, x, y = (np.concatenate(c) for c in zip(*held))
            parts = [np.stack((x[kind == k], y[kind == k])) for k in range(3)]
            for columns in work(parts, cell // blocks == cell % blocks):
                yield pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)) for c in columns], list(names))

        now, held = None, []
        for batch in batches:
            cell, kind, x, y = (c.to_numpy() for c in batch.columns)
            cuts = [0, *(np.flatnonzero(np.diff(cell)) + 1).tolist(), len(cell)]
            for a, b in zip(cuts, cuts[1:]):
                if a < b:
                    if held and cell[a] != now:
                        yield from done(now, held)
                        held = []
                    now = int(cell[a])
                    held.append((kind[a:b], x[a:b], y[a:b]))
        if held:
            yield from done(now, held)

    return run


def _run(members: DataFrame, edges: DataFrame | None, blocks: int | None, work: Callable, *names: str) -> DataFrame:
    blocks = blocks or max(1, math.ceil(members.count() / AT_ONCE))
    rows = _cells(members, edges, blocks).repartitionByRange(blocks * (blocks + 1) // 2, "cell").sortWithinPartitions("cell")
    return rows.mapInArrow(_by_cell(blocks, work, names), ", ".join(f"{n} long" for n in names))


def shared_groups(members: DataFrame, blocks: int | None = None) -> DataFrame:
    """src < dst, w: the pairs of members that share w groups; members(member, grp): distinct long ids, best written."""
    return _run(members, None, blocks, _pairs, "src", "dst", "w")


def count_shared(members: DataFrame, edges: DataFrame, blocks: int | None = None) -> DataFrame:
    """released, shared: how many pairs share a group, and how many of edges (src < dst, distinct) are such pairs."""
    cells = _run(members, edges, blocks, _counts, "pairs", "hits")
    return cells.agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("released"), F.coalesce(F.sum("hits"), F.lit(0)).alias("shared"))
