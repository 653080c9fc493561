"""Triangles by colours of vertices against brute force; no wedge is joined or shuffled."""

import random
from itertools import combinations

import pytest

from blockgraph.metrics import graphs as mg
from blockgraph.plans import triangles as tr
from blockgraph.queries.registry import QUERIES


@pytest.mark.parametrize("colours", [1, 2, 3, 5])
def test_triangles_of_any_number_of_colours(spark, monkeypatch, colours):
    rnd, unit, edges = random.Random(3), 1000, set()
    for run in (0, 3):
        ids = [run * unit + k for k in range(40)]
        edges |= {(a, b) for a, b in combinations(ids, 2) if rnd.random() < 0.25 or a == ids[0]}
    rows = [(a, b) if rnd.random() < 0.5 else (b, a) for a, b in sorted(edges)]
    want = {run: sum(1 for x in combinations(range(run * unit, run * unit + 40), 3) if all(p in edges for p in combinations(x, 2))) for run in (0, 3)}
    frame = spark.createDataFrame(rows, "src long, dst long")
    monkeypatch.setattr(tr, "LOOKS", 50)
    assert {r["unit"]: r["triangles"] for r in tr.triangles_by(frame, unit, colours).collect()} == want
    assert tr.triangles_by(frame, None, colours).first()["triangles"] == sum(want.values())


def test_small_steps_and_stars(monkeypatch):
    import numpy as np

    monkeypatch.setattr(tr, "LOOKS", 3)
    monkeypatch.setattr(tr, "MARKS", 10)

    u, v = np.array([0, 0, 0, 1, 2]), np.array([1, 2, 3, 2, 3])
    assert tr.closed_wedges(5, u, v).sum() == 2
    star = np.zeros(5000, np.int64), np.arange(1, 5001)
    assert tr.closed_wedges(5001, *star).sum() == 0
    src, dst = tr.unpacked(tr.packed(np.array([5, -7, 5]), np.array([-(1 << 60), 9, 3])), 3)
    assert sorted(zip(src.tolist(), dst.tolist())) == [(-7, 9), (5, -(1 << 60)), (5, 3)]


def test_no_edges(spark):
    assert mg.triangle_count(spark.createDataFrame([], "src long, dst long")).first()[0] == 0


def test_wedges_are_not_joined(spark, sf):
    plan = QUERIES["triangle_count"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan
