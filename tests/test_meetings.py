"""Pairs that share groups, in several blocks, against brute force; no shuffle holds a pair."""

from collections import Counter, defaultdict
from itertools import combinations

import pytest

from blockgraph.plans.meetings import count_shared, shared_groups
from blockgraph.queries.registry import QUERIES


@pytest.mark.parametrize("blocks", [1, 2, 3, 7])
def test_pairs_of_any_number_of_blocks(spark, blocks):
    rows = sorted({(m * 10_007 % 83 - 20, m * m % 29) for m in range(400)})
    members = spark.createDataFrame(rows, "member long, grp long")
    having = defaultdict(list)
    for m, g in rows:
        having[g].append(m)
    want = Counter(p for ms in having.values() for p in combinations(sorted(ms), 2))
    got = shared_groups(members, blocks).collect()
    assert len(got) == len(want) and {(r["src"], r["dst"]): r["w"] for r in got} == want
    edges = sorted(set(list(want)[::3]) | {(-20, 999), (500, 501), (-5, 60)})
    row = count_shared(members, spark.createDataFrame(edges, "src long, dst long"), blocks).first()
    assert (row["released"], row["shared"]) == (len(want), sum(e in want for e in edges))


def test_no_members(spark):
    none = spark.createDataFrame([], "member long, grp long")
    assert shared_groups(none).count() == 0
    assert tuple(count_shared(none, spark.createDataFrame([(1, 2)], "src long, dst long")).first()) == (0, 0)


@pytest.mark.parametrize("name", ["g2_coactivity", "edge_overlap"])
def test_pairs_are_not_shuffled(spark, sf, name):
    plan = QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "MapInArrow" in plan
