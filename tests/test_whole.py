"""Queries over the whole graph against brute force."""

from collections import Counter, defaultdict

import numpy as np

from blockgraph.queries import relational as rel
from blockgraph.queries import soft as qs
from blockgraph.queries import workloads as qw
from blockgraph.soft import predict


def test_degree_pairs_and_grid_of_the_whole_graph(spark, sf):
    edges = [(r["src"], r["dst"]) for r in rel._graph(spark, sf).select("src", "dst").collect()]
    degree, having = Counter(v for e in edges for v in e), defaultdict(list)
    for v, d in degree.items():
        having[d].append(v)
    want = sorted((v, w) for v, d in degree.items() for w in having.get(d + 1, []))
    rows, classes = rel.theta_degree_pairs_all(spark, sf).collect(), defaultdict(list)
    for r in rows:
        classes[r["deg"]].append(r["id"])
    got = sorted((v, w) for d, low in classes.items() for v in low for w in classes.get(d + 1, []))
    assert got == want and len(got) > rel.theta_degree_pairs(spark, sf).count()
    above, below = Counter(v for v, _ in want), Counter(w for _, w in want)
    assert len(rows) == len(degree) and all((r["n_above"], r["n_below"]) == (above[r["id"]], below[r["id"]]) for r in rows)

    lab = {r["id"]: r["lab"] for r in rel._labels(rel._graph(spark, sf)).collect()}
    hits = Counter(tuple(sorted((lab[s], lab[d]))) for s, d in edges)
    grid = {(r["a"], r["b"]): r["hit"] for r in rel.outer_block_grid_all(spark, sf).collect()}
    assert grid == {(a, b): hits[a, b] for a in range(rel.K) for b in range(a, rel.K)}
    assert sum(grid.values()) == len(edges)


def test_every_user_gets_unseen_items(spark, sf):
    edges, left, right, cat = qs._state(spark, sf)
    vectors = lambda df: dict(sorted((r["id"], np.array(r["vec"])) for r in df.collect()))
    ml, mr = vectors(left), vectors(right)
    mean = np.zeros((qs.A, qs.B))
    for r in cat.collect():
        mean[r["a"], r["b"]] += r["p"] * (r["c"] + 1)
    seen = {(r["src"], r["dst"]) for r in edges.collect()}
    items, all_mr, want = list(mr), np.array(list(mr.values())), {}
    for u, x in ml.items():
        scores = np.round(all_mr @ (x @ mean), 9)
        order = [i for i in np.argsort(-scores, kind="stable") if (u, items[i]) not in seen][:5]
        want |= {(u, k + 1): (items[i], scores[i]) for k, i in enumerate(order)}
    found = predict.top_n_all(edges, left, right, cat, qs._values(spark), 5, block=60).collect()
    got = {(r["src"], r["rank"]): (r["dst"], r["pred"]) for r in found}
    assert len(found) == len(got) and set(got) == set(want)
    assert all(got[k][0] == want[k][0] and abs(got[k][1] - want[k][1]) < 1e-8 for k in want)
    assert {u for u, _ in got} == set(ml)


def test_expansion_at_the_surveyed_sizes(spark, sf):
    assert {r["n"] for r in qw.workload_expansion_cost(spark, sf).collect()} == {200, 2000}


def test_asked_users_and_items_are_not_joined_pair_by_pair(spark, sf):
    plan = qs.recommend_top_n(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapGroupsInArrow" in plan and "left_anti" not in plan.lower() and "LeftAnti" not in plan


def test_best_items_of_a_tile_with_equal_scores():
    import pyarrow as pa

    rows = [(0, 1, None, [1.0]), (0, 2, None, [0.0]), *[(1, k, None, [float(x)]) for k, x in enumerate((3, 5, 5, 5, 1))], (2, 1, 1, None)]
    table = pa.table({name: [r[k] for r in rows] for k, name in enumerate(("kind", "x", "y", "vec"))})
    out = predict._best_of_tile(np.eye(1), 2)(table).to_pydict()
    assert list(zip(out["src"], out["dst"])) == [(1, 2), (1, 3), (2, 0), (2, 1)]
    assert len(predict._best_of_tile(np.eye(1), 9)(table)) == 4 + 5
