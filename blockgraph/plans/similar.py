"""Pairs of vectors with a large inner product: blocks of vectors meet as matrices, what is near the bound is summed in order."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = 1 << 15
CELLS = 1 << 23
EXACT = 1 << 17


def _above(ids: list[np.ndarray], vecs: list[np.ndarray], same: bool, least: float) -> Iterator[list[np.ndarray]]:
    """src, dst, cos of the pairs of two blocks whose products, added up from the first component on, exceed least."""
    (x_ids, y_ids), (x, y) = ids, vecs
    with np.errstate(all="ignore"):
        nx, ny = np.linalg.norm(x, axis=1), np.linalg.norm(y, axis=1)
        odd_x, odd_y = ~np.isfinite(nx), ~np.isfinite(ny)
        largest = ny[~odd_y].max(initial=0.0)
        rows = max(1, CELLS // max(1, len(y)))
        for at in range(0, len(x), rows):
            cut = slice(at, at + rows)
            slack = 1e-14 * (x.shape[1] + 8) * nx[cut] * largest  # far above the rounding of any order of adding
            near = ~(x[cut] @ y.T <= (least - slack)[:, None])
            near[odd_x[cut]] = True
            near[:, odd_y] = True
            u, v = np.nonzero(near)
            u += at
            if same:
                later = x_ids[u] < y_ids[v]
                u, v = u[later], v[later]
            for k in range(0, len(u), EXACT):
                i, j = u[k : k + EXACT], v[k : k + EXACT]
                cos = np.zeros(len(i))
                for c in range(x.shape[1]):
                    cos += x[i, c] * y[j, c]
                kept = (cos > least) | np.isnan(cos)
                kept &= x_ids[i] != y_ids[j]
                a, b = x_ids[i[kept]], y_ids[j[kept]]
                if len(a):
                    yield [np.minimum(a, b), np.maximum(a, b), cos[kept]]


def _cells(blocks: int, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def done(key: tuple[int, int], held: list) -> Iterator[pa.RecordBatch]:
            kind, ids, vec = (np.concatenate(c) for c in zip(*held))
            vec, same = vec.reshape(len(ids), key[0]).astype(float), key[1] // blocks == key[1] % blocks
            parts = [kind == 0, kind == 0 if same else kind == 1]
            for columns in _above([ids[p] for p in parts], [vec[p] for p in parts], same, least):
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["src", "dst", "cos"])

        now, held = None, []
        for batch in batches:
            size, cell, kind, ids = (batch.column(c).to_numpy() for c in range(4))
            cuts = [0, *(np.flatnonzero((np.diff(size) != 0) | (np.diff(cell) != 0)) + 1).tolist(), len(cell)]
            for a, b in zip(cuts, cuts[1:]):
                if a < b:
                    key = int(size[a]), int(cell[a])
                    if held and key != now:
                        yield from done(now, held)
                        held = []
                    now = key
                    held.append((kind[a:b], ids[a:b], batch.column(4).slice(a, b - a).flatten().to_numpy(zero_copy_only=False)))
        if held:
            yield from done(now, held)

    return run


def similar_pairs(vectors: DataFrame, least: float, block: int = BLOCK) -> DataFrame:
    """src < dst, cos: all pairs of vectors(id, vec) of one length whose inner product exceeds least (nan does); vectors
    that are null or hold nulls have no pairs."""
    whole = vectors.where(F.col("vec").isNotNull() & F.col("id").isNotNull() & ~F.exists("vec", lambda x: x.isNull()))
    blocks = max(1, math.ceil(whole.count() / block))
    own, other = F.col("own"), F.col("other")
    dealt = whole.select(F.size("vec").alias("size"), F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("own"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"), F.col("id").cast("long").alias("id"), "vec")
    low = F.least("own", "other")
    rows = dealt.select("size", (low * blocks + F.greatest("own", "other")).alias("cell"), F.when(own == low, 0).otherwise(1).alias("kind"), "id", "vec")
    placed = rows.repartitionByRange(blocks * (blocks + 1) // 2, "size", "cell").sortWithinPartitions("size", "cell")
    return placed.mapInArrow(_cells(blocks, least), "src long, dst long, cos double")
