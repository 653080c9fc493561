"""Column functions and their SQL registration."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..hard.stats import pair_cost, xlogx

__all__ = ["block_entropy", "dot", "log_sum_exp", "pair_cost", "register", "vec_sum", "xlogx"]


def dot(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda s, v: s + v)


def log_sum_exp(vec: Column) -> Column:
    top = F.array_max(vec)
    return top + F.ln(F.aggregate(vec, F.lit(0.0), lambda s, x: s + F.exp(x - top)))


def vec_sum(vec: Column, size: int) -> Column:
    """Element-wise sum of vectors of a known size, as an aggregate that combines before the shuffle."""
    return F.array(*[F.sum(F.get(vec, F.lit(k))) for k in range(size)])


def block_entropy(hits: Column, misses: Column) -> Column:
    """Entropy of the block pairs whose hits and misses two arrays list."""
    return F.aggregate(F.zip_with(hits, misses, lambda hit, miss: pair_cost(hit, miss)), F.lit(0.0), lambda s, x: s + x)


def register(spark: SparkSession) -> None:
    """Temporary SQL functions: xlogx, pair_cost, block_entropy, soft_predict (a bilinear form), the aggregate vec_sum (an
    Arrow function, vectors of any size) and the table function draw_pairs."""

    @F.pandas_udf("array<double>")
    def vec_sum_any(vectors: pd.Series) -> list:
        return np.sum(np.stack(vectors.to_list()), axis=0).tolist() if len(vectors) else []

    spark.udf.register("vec_sum", vec_sum_any)
    g = "CASE WHEN {0} > 0 THEN {0} * ln({0}) ELSE 0D END"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION xlogx(x DOUBLE) RETURNS DOUBLE RETURN {g.format('x')}")
    cost = lambda hit, miss: f"CASE WHEN {hit} >= 0 AND {miss} >= 0 THEN ({g.format(f'({hit} + {miss})')}) - ({g.format(hit)}) - ({g.format(miss)}) ELSE 0D END"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION pair_cost(hit DOUBLE, miss DOUBLE) RETURNS DOUBLE RETURN {cost('hit', 'miss')}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION block_entropy(hits ARRAY<DOUBLE>, misses ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(hits, misses, (h, m) -> {cost('h', 'm')}), 0D, (s, x) -> s + x)")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION soft_predict(ml ARRAY<DOUBLE>, mr ARRAY<DOUBLE>, matrix ARRAY<DOUBLE>) RETURNS DOUBLE RETURN "
        "aggregate(sequence(0, size(ml) - 1), 0D, (s, a) -> s + ml[a] * aggregate(sequence(0, size(mr) - 1), 0D, (q, b) -> q + mr[b] * matrix[a * size(mr) + b]))"
    )

    @F.udtf(returnType="i long, j long")
    class DrawPairs:
        """cnt distinct pairs i < j of 0 .. size - 1."""

        def eval(self, size: int, cnt: int, seed: int):
            import numpy as np

            from ..anonymize.release import feistel, unrank

            i, j = unrank(feistel(np.arange(cnt), size * (size - 1) // 2, (seed,)), size)
            yield from zip(i.tolist(), j.tolist(), strict=True)

    spark.udtf.register("draw_pairs", DrawPairs)
