"""Scores of blocks with very many pairs, to the last bit, as DuckDB's logarithm gives them."""

import math

import pytest

from blockgraph.hard import score
from blockgraph.hard.problems import ObservedWeights

SIZES = (301_007, 299_993)
PAIRS = {(0, 0): 301_007 * 301_006 / 2, (0, 1): 301_007.0 * 299_993, (1, 1): 299_993 * 299_992 / 2}


def g(x):
    return x * math.log(x) if x > 0 else 0.0


def cost(hit, miss):
    return g(hit + miss) - g(hit) - g(miss) if hit >= 0 and miss >= 0 else 0.0


def simple_case(spark, hits):
    rows = [(a, b, SIZES[a], SIZES[b], PAIRS[a, b], hits[a, b], PAIRS[a, b] - hits[a, b]) for a, b in PAIRS]
    stats = spark.createDataFrame(rows, "a int, b int, na long, nb long, pairs double, hit long, miss double")
    cases = [(i, i % 2, 1 + i % 7, 2 + i % 5) for i in range(70)]
    labels = spark.createDataFrame([(i, y) for i, y, _, _ in cases], "id long, lab int")
    links = spark.createDataFrame([(i, b, (x0, x1)[b]) for i, _, x0, x1 in cases for b in (0, 1)], "id long, b int, x long")
    cell = lambda a, b: (hits[min(a, b), max(a, b)], PAIRS[min(a, b), max(a, b)] - hits[min(a, b), max(a, b)])
    return stats, labels, links, cases, cell


@pytest.mark.parametrize("seed", range(2))
def test_scores_of_large_blocks_to_the_last_bit(spark, seed):
    hits = {(0, 0): 4_000_037 + seed, (0, 1): 9_000_011 + 3 * seed, (1, 1): 4_100_003 + 7 * seed}
    stats, labels, links, cases, cell = simple_case(spark, hits)
    table, exact = {}, {}
    for i, y, *x in cases:
        s = [n - (b == y) for b, n in enumerate(SIZES)]
        for a in (0, 1):
            parts, whole = [], []
            for b in (0, 1):
                hit, miss = cell(a, b)
                fewer = SIZES[b] - (a == b)
                enter, leave = cost(hit, miss + SIZES[b]) - cost(hit, miss), cost(hit, miss) - cost(hit, miss - fewer)
                if a == y:
                    parts.append((leave, cost(hit, miss) - cost(hit - x[b], miss - (s[b] - x[b])) - leave))
                else:
                    parts.append((enter, cost(hit + x[b], miss + (s[b] - x[b])) - cost(hit, miss) - enter))
                gone_hit, gone_all = (x[b], s[b]) if a == y else (x[a], s[a]) if b == y else (0, 0)
                h, m = hit - gone_hit, miss - (gone_all - gone_hit)
                whole.append(cost(h + x[b], m + s[b] - x[b]) - cost(h, m))
            table[i, a] = sum(c for _, c in parts) + sum(t for t, _ in parts)
            exact[i, a] = sum(whole)
    assert {(r["id"], r["a"]): r["score"] for r in score.score_table(links, labels, stats).collect()} == table
    assert {(r["id"], r["a"]): r["score"] for r in score.score_exact(links, labels, stats).collect()} == exact


def test_scores_of_many_ratings_to_the_last_bit(spark):
    cells = {(a, b, k): 70_000_003 + 1_000_211 * a + 37 * b + 500_009 * k for a in (0, 1) for b in (0, 1) for k in range(1, 25)}
    sums = {(a, b): sum(cells[a, b, k] for k in range(1, 25)) for a in (0, 1) for b in (0, 1)}
    found = [(i, b, k, float(1 + (i + b + k) % 4)) for i in range(60) for b in (0, 1) for k in range(1, 25)]
    labels = spark.createDataFrame([(i, i % 2) for i in range(60)], "id long, lab int")
    links = spark.createDataFrame(found, "id long, b int, k int, x double")
    counts = spark.createDataFrame([(*c, float(n)) for c, n in cells.items()], "a int, b int, k int, n double")
    problem = ObservedWeights(links, 2, 2)
    got = {(r["id"], r["a"]): r["score"] for r in problem.scores(links, labels, labels, counts).collect()}
    for i in range(60):
        for a in (0, 1):
            own, want = a == i % 2, 0.0
            for b in (0, 1):
                x = {k: v for j, c, k, v in found if (j, c) == (i, b)}
                base = sums[a, b] - own * sum(x.values())
                want += g(base + sum(x.values())) - g(base)
                for k in x:
                    base = cells[a, b, k] - own * x[k]
                    want -= g(base + x[k]) - g(base)
            assert got[i, a] == want
