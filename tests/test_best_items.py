"""The best unseen items of all users: bounds pass over runs of items, and no vector is copied to meet others."""

import numpy as np
import pytest

from blockgraph.queries import soft as qs
from blockgraph.soft import predict


def of_packs(weight, vec, seen, n, packs):
    order = predict._near_order(weight, predict.BATCH)
    place = np.argsort(order)
    who, what = np.array(sorted((place[u], i) for u, i in seen)).reshape(-1, 2).T
    best = predict._Best([order, *weight[order].T], [who.astype(np.int32), what], n)
    for part in np.array_split(np.random.default_rng(5).permutation(len(vec)), packs):
        own = part[predict._near_order(vec[part], predict.LEAF)]
        best.meet([own, *vec[own].T])
    return best.rows().to_pylist()


@pytest.mark.parametrize("kind", ["members", "equal", "signed", "few"])
def test_bounds_lose_no_item(monkeypatch, kind):
    monkeypatch.setattr(predict, "LEAF", 16)
    monkeypatch.setattr(predict, "BATCH", 8)
    rng = np.random.default_rng(3)
    vec, weight = rng.dirichlet(np.ones(3), 900), rng.random((50, 3)) + 2.5
    if kind == "equal":
        vec = vec[rng.integers(0, 9, 900)]
    if kind == "signed":
        vec, weight = rng.normal(size=(900, 3)), rng.normal(size=(50, 3))
    if kind == "few":
        vec = vec[:6]
    seen = {(u, i) for u in range(50) for i in np.argsort(-(vec @ weight[u]), kind="stable")[: u % 6]}
    found = of_packs(weight, vec, seen, 4, 3)
    got = {(r["src"], r["rank"]): r["dst"] for r in found}
    want = {}
    for u in range(50):
        score = np.round(vec @ weight[u], 9)
        left = [i for i in np.lexsort((np.arange(len(vec)), -score)) if (u, i) not in seen][:4]
        want |= {(u, k + 1): i for k, i in enumerate(left)}
    assert got == want and len(found) == len(got)


def test_most_runs_of_items_are_passed_over(monkeypatch):
    rng = np.random.default_rng(4)
    met, plain = [], predict._Best._add
    monkeypatch.setattr(predict._Best, "_add", lambda self, at, users, pred, ids, seen: met.append(pred.size) or plain(self, at, users, pred, ids, seen))
    weight, vec = rng.dirichlet(np.ones(2), 1024) @ (rng.random((2, 3)) / 2 + 2.8), rng.dirichlet(np.ones(3), 60_000)
    assert len(of_packs(weight, vec, {(0, 0)}, 5, 2)) == 5 * 1024
    assert sum(met) < len(weight) * len(vec) / 5


def test_no_vector_is_copied_to_meet_others(spark, sf):
    plan = qs.recommend_top_n_all(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "explode" not in plan and "Generate" not in plan and "FlatMapGroupsInArrow" in plan
