"""Pairs of similar vectors in several blocks against brute force, nulls, nan and short vectors among them."""

import math

import numpy as np
import pytest

from blockgraph.plans.similar import similar_pairs
from blockgraph.queries.registry import QUERIES


@pytest.mark.parametrize("block", [1000, 50, 23])
def test_similar_pairs_to_the_last_bit(spark, block):
    rng = np.random.default_rng(4)
    rows = [(i * 7 - 90, [float(np.float32(x)) for x in rng.normal(size=6) / 2]) for i in range(100)]
    rows += [(1001, None), (1002, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (1003, [5.0, 5.0]), (1004, [5.0, -1.0]), (1005, [math.nan] * 6), (1006, [math.inf, 0.0, 0.0, 0.0, 0.0, 0.0]), (1007, [])]
    rows += [(2000, [0.5, 0.0, 0.0, 0.0, 0.0, 0.0]), (2001, [0.6, 0.0, 0.0, 0.0, 0.0, 0.0])]
    want = {}
    for i, x in rows:
        for j, y in rows:
            if i < j and x is not None and y is not None and None not in x + y and len(x) == len(y):
                total = 0.0
                for a, b in zip(x, y):
                    total += a * b
                if total > 0.3 or math.isnan(total):
                    want[i, j] = repr(total)
    got = similar_pairs(spark.createDataFrame(rows, "id long, vec array<double>"), 0.3, block).collect()
    assert len(got) == len(want) and {(r["src"], r["dst"]): repr(r["cos"]) for r in got} == want


def test_no_pair_is_joined(spark, sf):
    plan = QUERIES["g3_similarity"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "MapInArrow" in plan
