"""Queries that once made their data up follow the given tables."""

from collections import defaultdict

import pytest

from blockgraph.queries.registry import QUERIES
from blockgraph.sources import tables as t


@pytest.fixture()
def urgent(spark, sf):
    segment = {r["c_custkey"]: r["c_mktsegment"] for r in t.table(spark, sf, "customer").collect()}
    n = defaultdict(int)
    for r in t.table(spark, sf, "orders").collect():
        n[segment[r["o_custkey"]], r["o_orderpriority"]] += 1
    segments, priorities = (sorted({k[i] for k in n}) for i in (0, 1))
    mean = sum(n.values()) / len(n)
    return {(2 * segments.index(s), 2 * priorities.index(p) + 1) for (s, p), m in n.items() if m > mean}


def test_labelings_of_the_graph_of_orders(spark, sf, urgent):
    assert {tuple(r) for r in t.g10_urgency(spark, sf).collect()} == urgent
    rows = QUERIES["brute_force_toy"](spark, sf).collect()
    assert {r["labeling"] for r in rows} == set(range(1 << len({v for e in urgent for v in e})))


def test_certificate_of_the_graph_of_orders(spark, sf):
    from blockgraph.hard import fit
    from blockgraph.graph import vertices
    edges = t.g10_urgency(spark, sf)
    now = fit.entropy_of(edges, vertices(edges).selectExpr("id", "CAST(id % 2 AS INT) AS lab"), 2)
    moved = [fit.entropy_of(edges, vertices(edges).selectExpr("id", f"CAST(IF(id = {v}, 1 - id % 2, id % 2) AS INT) AS lab"), 2) for v in (r["id"] for r in vertices(edges).collect())]
    row = QUERIES["local_opt_certificate"](spark, sf).first()
    assert abs(row["gain"] - max(0.0, now - min(moved))) < 1e-6 and row["locally_optimal"] == (now - min(moved) <= 1e-9)


def test_categories_are_those_of_the_ratings(spark, sf, tmp_path):
    assert any(f.endswith("lineitem.parquet") for f in QUERIES["init_cat"](spark, sf).inputFiles())
    for name in ("orders", "lineitem"):
        rows = t.table(spark, sf, name)
        (rows.where("l_quantity <= 20") if name == "lineitem" else rows).write.parquet(f"{tmp_path}/{name}.parquet")
    rows = QUERIES["init_cat"](spark, str(tmp_path)).collect()
    assert {r["c"] for r in rows} == {0, 1}


def test_reach_follows_the_orders_of_a_customer(spark, sf):
    orders = t.table(spark, sf, "orders").collect()
    first = min(orders, key=lambda r: r["o_orderkey"])
    when = lambda r: (r["o_orderdate"], r["o_orderkey"])
    want = {r["o_orderkey"] for r in orders if r["o_custkey"] == first["o_custkey"] and when(r) >= when(first)}
    assert {r["id"] for r in QUERIES["recursive_reach"](spark, sf).collect()} == want
