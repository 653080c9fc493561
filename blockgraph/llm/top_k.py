"""Exact top-k inner products: vectors by descending length, SVD-rotated partial sums, Cauchy-Schwarz bounds.

Components are turned into whole numbers floor(scale * x). Candidates are dealt by descending length into bands, which
are written once, so that every vector lies in just one; each band meets each block of queries in one task. The longest band goes first; the k-th score it gives a query is a
floor for all other bands. Inside a task candidates come in descending length: a block whose longest vector cannot reach
a query's floor by Cauchy-Schwarz is skipped for it; for the rest the inner product over the leading coordinates of a
common rotation, plus the product of the lengths of what remains, bounds the score from above, and only pairs whose
bound reaches the floor are scored, in whole numbers. The rotation holds the right singular vectors of a sample of at
most SAMPLE vectors (chosen by a hash of vec_id); it only steers pruning, any rotation gives the same answer.

Defined results: vectors that are null, or hold a null or non-finite component, take no part; nor do vectors of another
length than the commonest one (ties: the longer); of rows that share a vec_id the smallest vector stands for all; rows
with a null vec_id are left out; a query meets every other vec_id; ties go to the smaller vec_id; other columns are
ignored. Scores beyond 64 bits are cut to the ends of that range.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ._common import materialise

SAMPLE = 4096
BLOCK = 1024
QUERY_BLOCK = 4096
TASK_BYTES = 32 << 20
EXACT = float(1 << 53)


def usable(vector: Column) -> Column:
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vector.isNotNull() & (F.size(vector) > 0) & ~F.coalesce(bad, F.lit(True))


def whole_vectors(vectors: DataFrame, scale: int) -> DataFrame:
    """vec_id and v, one row for each vec_id: whole components as doubles."""
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("x")).where(F.col("vec_id").isNotNull() & usable(F.col("x")))
    whole = rows.select("vec_id", F.transform("x", lambda x: F.rint(x * scale) - F.when(F.rint(x * scale) > x * scale, 1.0).otherwise(0.0)).alias("v"))
    return whole.groupBy("vec_id").agg(F.min("v").alias("v"))


def _matrix(column: pa.ChunkedArray | pa.Array, dims: int) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return flat.flatten().to_numpy(zero_copy_only=False).reshape(-1, dims)


def _exact_scores(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """left x right inner products: in doubles where all partial sums stay exact, in whole numbers of any size else."""
    if np.abs(left).max(initial=0) * np.abs(right).max(initial=0) * left.shape[1] < EXACT:
        return left @ right.T
    whole = np.vectorize(int, otypes=[object])
    return whole(left) @ whole(right).T


class Best:
    """The k best (score, vec_id) of each query so far."""

    def __init__(self, queries: int, k: int, floor: np.ndarray) -> None:
        self.k, self.floor = k, floor.copy()
        self.found: list[list[tuple]] = [[] for _ in range(queries)]

    def add(self, q: int, scores, ids) -> None:
        merged = sorted([*self.found[q], *zip(scores, ids, strict=True)], key=lambda x: (-x[0], x[1]))[: self.k]
        self.found[q] = merged
        if len(merged) == self.k:
            self.floor[q] = max(self.floor[q], float(merged[-1][0]) * (1 - 1e-15) - 1)


def search(ids: np.ndarray, candidates: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, rotation: np.ndarray, floor: np.ndarray, k: int, lead: int, block: int = BLOCK) -> list[list[tuple]]:
    """For each query its k best candidates with a score of at least its floor, pruned as described above."""
    best = Best(len(query_ids), k, floor)
    if not len(ids) or not len(query_ids):
        return best.found
    length = np.linalg.norm(candidates, axis=1)
    order = np.argsort(-length, kind="stable")
    ids, candidates, length = ids[order], candidates[order], length[order]
    turned, asked = candidates @ rotation, queries @ rotation
    rest, asked_rest = np.linalg.norm(turned[:, lead:], axis=1), np.linalg.norm(asked[:, lead:], axis=1)
    reach = np.linalg.norm(queries, axis=1)
    for at in range(0, len(ids), block):
        own = slice(at, min(at + block, len(ids)))
        slack = 1 + 1e-9 * reach * length[at]
        live = np.flatnonzero(reach * length[at] + slack >= best.floor)
        if not len(live):
            if (best.floor >= reach * length[at] + slack).all():
                break
            continue
        for part in np.array_split(live, math.ceil(len(live) / 256)):
            bound = asked[part, :lead] @ turned[own, :lead].T + np.outer(asked_rest[part], rest[own])
            open_ = (bound + slack[part, None] >= best.floor[part, None]) & (ids[None, own] != query_ids[part, None])
            if open_.mean() > 0.05:
                scores = _exact_scores(queries[part], candidates[own])
                for i, q in enumerate(part.tolist()):
                    cols = np.flatnonzero(open_[i])
                    _take(best, q, scores[i, cols], ids[own][cols], k)
            else:
                for i in np.flatnonzero(open_.any(axis=1)).tolist():
                    cols = np.flatnonzero(open_[i])
                    _take(best, int(part[i]), _exact_scores(queries[part[i]][None], candidates[own][cols])[0], ids[own][cols], k)
    return best.found


def _take(best: Best, q: int, scores: np.ndarray, ids: np.ndarray, k: int) -> None:
    if scores.dtype != object and len(scores) > k:
        least = max(np.partition(scores, len(scores) - k)[len(scores) - k], best.floor[q])
        keep = scores >= least
        scores, ids = scores[keep], ids[keep]
    if len(scores):
        best.add(q, scores.tolist(), ids.tolist())


def _tile(k: int, dims: int, rotation: np.ndarray, lead: int):
    def tile(candidates: pa.Table, queries: pa.Table) -> pa.Table:
        query_ids = queries.column("vec_id").to_numpy()
        floor = queries.column("floor").to_numpy()
        found = search(candidates.column("vec_id").to_numpy(), _matrix(candidates.column("v"), dims), query_ids, _matrix(queries.column("v"), dims), rotation, floor, k, lead)
        rows = [(q, i, min(max(int(s), -(1 << 63)), (1 << 63) - 1)) for q, own in zip(query_ids.tolist(), found, strict=True) for s, i in own]
        columns = list(zip(*rows, strict=True)) or [(), (), ()]
        return pa.table([pa.array(c, pa.int64()) for c in columns], names=["query_id", "vec_id", "score"])

    return tile


def rotation_of(sample: np.ndarray, dims: int) -> np.ndarray:
    return np.linalg.svd(sample, full_matrices=True)[2].T if len(sample) else np.eye(dims)


def top_k(spark: SparkSession, vectors: DataFrame, is_query: Column, k: int = 10, scale: int = 1024) -> DataFrame:
    """query_id, rank, vec_id and score: the k largest inner products of each query; is_query is over vec_id."""
    whole = whole_vectors(vectors, scale)
    shape = whole.groupBy(F.size("v").alias("dims")).agg(F.count("*").alias("n"), F.count_if(is_query).alias("q")).orderBy(F.desc("n"), F.desc("dims")).first()
    empty = "query_id long, rank int, vec_id long, score long"
    if shape is None:
        return spark.createDataFrame([], empty)
    dims, n, n_queries = shape["dims"], shape["n"], shape["q"]
    whole = whole.where(F.size("v") == dims)
    sample = whole.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).select("v").toArrow()
    rotation, lead = rotation_of(_matrix(sample.column("v"), dims), dims), max(1, dims // 4)
    bands = max(1, min(math.ceil(n / BLOCK), max(spark.sparkContext.defaultParallelism, math.ceil(n * dims * 8 / TASK_BYTES))))
    blocks = max(1, math.ceil(n_queries / QUERY_BLOCK))
    length = F.aggregate("v", F.lit(0.0), lambda total, x: total + x * x)
    banded = whole.withColumn("length", length).repartitionByRange(bands, F.desc("length"), "vec_id").select("vec_id", "v", F.spark_partition_id().alias("band"))
    banded = materialise(banded, "banded")  # the cuts are sampled: a second evaluation would cut elsewhere
    queries = whole.where(is_query).withColumns({"block": F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"), "floor": F.lit(float("-inf"))})

    def meet(which: Column, asked: DataFrame, first: int, last: int) -> DataFrame:
        dealt = banded.where(which).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
        sent = asked.withColumn("band", F.explode(F.sequence(F.lit(first), F.lit(last))))
        sent = sent.toDF(*sent.columns)  # columns of their own: both sides come from one table
        return dealt.groupBy("band", "block").cogroup(sent.groupBy("band", "block")).applyInArrow(_tile(k, dims, rotation, lead), "query_id long, vec_id long, score long")

    found = materialise(meet(F.col("band") == 0, queries, 0, 0), "longest")
    if bands > 1:
        floors = found.groupBy("query_id").agg(F.min("score").alias("least"), F.count("*").alias("n")).where(F.col("n") == k).select(F.col("query_id").alias("vec_id"), F.col("least").cast("double").alias("least"))
        raised = queries.join(floors, "vec_id", "left").withColumn("floor", F.coalesce("least", "floor")).drop("least")
        found = found.unionAll(meet(F.col("band") > 0, raised, 1, bands - 1))
    ranked = found.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
