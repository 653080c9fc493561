"""Queries at larger tables: what the driver and a task hold, what is computed once."""

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from blockgraph import rng
from blockgraph.anonymize import release
from blockgraph.em.loop import Stop, Trace
from blockgraph.eval import grid, scaling
from blockgraph.eval import workloads as experiments
from blockgraph.hard import fit as hf
from blockgraph.hard import kernel, packed
from blockgraph.metrics import graphs
from blockgraph.plans import drawn, placement
from blockgraph.plans.state import write_state
from blockgraph.queries import workloads
from blockgraph.rng import portable_numpy
from blockgraph.soft import kernel as soft_kernel
from blockgraph.sources import tables


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_many_rows_in_few_bytes_stay_away_from_the_driver(spark, monkeypatch):
    rows = write_state(spark.range(300_000).selectExpr("0L AS a", "id AS rank", "id % 7 AS id"), "ranks")
    counts = spark.createDataFrame([(0, 0, 0, 10**6, 1000, 1000, 5)], "replica int, a int, b int, pairs long, na long, nb long, cnt long")
    made = release.expand(counts, rows, 1)
    assert "BroadcastHashJoin" not in plan_of(made) and made.count() == 5
    small = spark.range(5)
    assert "BroadcastHashJoin" in plan_of(spark.range(9).join(placement.by_rows(small, 5), "id"))
    assert "BroadcastHashJoin" not in plan_of(spark.range(9).join(placement.by_rows(small, placement.FEW + 1), "id"))
    edges = spark.createDataFrame([(k, k + 1) for k in range(6)] + [(0, 3)], "src long, dst long")
    hops = lambda: sorted(map(tuple, graphs.hop_distances(edges, spark.range(2)).collect()))
    few = hops()
    monkeypatch.setattr(placement, "FEW", 1)
    assert hops() == few and (0, 6, 4) in few


def heavy_graph(n, m, seed):
    rng = np.random.default_rng(seed)
    weight = 1 / (1.0 + np.arange(n)) ** 0.6
    pairs = np.unique(np.sort(rng.choice(n, (m, 2), p=weight / weight.sum()), axis=1), axis=0)
    pairs = pairs[pairs[:, 0] < pairs[:, 1]]
    return kernel.Graph(n, pairs[:, 0], pairs[:, 1])


def test_scores_looked_up_are_those_computed(monkeypatch):
    graph, lab = heavy_graph(400, 5000, 3), np.arange(400) % 6
    looked_up, chosen = kernel.table_scores(graph, lab, 6, np.arange(0, 400, 3)), np.arange(0, 400, 3)
    assert kernel.TableScores(*graph.counts(lab, 6), 2000, 100).upto > 5
    monkeypatch.setattr(kernel, "HELD", 0)
    assert np.array_equal(kernel.table_scores(graph, lab, 6, chosen), looked_up)
    monkeypatch.setattr(kernel, "PIECE", 50)
    best, gain = kernel.decided(graph, lab, 6, chosen, graph.counts(lab, 6))
    want = kernel.best_blocks(looked_up, lab[chosen])
    assert np.array_equal(best, want[0]) and np.array_equal(gain, want[1])


def test_rounds_that_repeat_labels_are_not_computed_again(monkeypatch):
    decided, calls = kernel.decided, []
    monkeypatch.setattr(kernel, "decided", lambda *a: calls.append(len(a[3])) or decided(*a))
    for frac in (1.0, 0.3):
        calls.clear()
        graph, lab = heavy_graph(500, 1800, 1), np.arange(500) % 20
        found = list(kernel.rounds(graph, lab, 20, frac, 200, 1))
        assert len(found) == 200 and len(calls) < 200
        for number, (after, entropy, moved) in enumerate(found, 1):  # each round from the labels before it, on its own
            chosen = np.arange(500) if frac == 1 else np.flatnonzero(portable_numpy(1, "choose", number, np.arange(500)) < frac)
            want = lab.copy()
            want[chosen] = decided(graph, lab, 20, chosen, graph.counts(lab, 20))[0]
            assert np.array_equal(after, want) and moved == (want != lab).sum() and entropy == graph.entropy(want, 20)
            lab = after


def test_slices_follow_the_number_of_blocks(monkeypatch):
    rng = np.random.default_rng(2)
    ratings = soft_kernel.Ratings.of(rng.integers(0, 50, 4000), rng.integers(0, 40, 4000), rng.integers(0, 5, 4000))

    def run():
        trace = Trace()
        return list(soft_kernel.soft_rounds(ratings, (8, 3, 5), None, 7, Stop(max_iter=3, tol=0.0), trace)), trace.entropies

    whole, seen, plain = run(), [], soft_kernel.edge_pass
    monkeypatch.setattr(soft_kernel, "SLICE_CELLS", 800)
    monkeypatch.setattr(soft_kernel, "edge_pass", lambda src, *rest: seen.append(len(src)) or plain(src, *rest))
    found = run()
    assert max(seen) == 100 and np.allclose(found[1], whole[1], rtol=1e-12)
    assert all(np.allclose(a, b) for a, b in zip(found[0][-1], whole[0][-1]))


def test_ids_without_a_training_row_have_no_position():
    ids, at = grid._positions(pa.chunked_array([[30, 10, 30], [20, 5]], pa.int64()))
    assert ids.tolist() == [5, 10, 20, 30] and at.tolist() == [3, 1, 3, 2, 0]
    left, where = grid._trained(ids, at, np.array([True, False, False, True, True]))
    assert left.tolist() == [5, 20, 30] and where.tolist() == [2, -1, 2, 1, 0]


def test_packed_rounds_make_the_moves_of_one_task(spark, monkeypatch):
    monkeypatch.setattr(packed, "ENDS", 300)
    rng = np.random.default_rng(5)
    pairs = sorted({(min(a, b), max(a, b)) for a, b in rng.integers(0, 90, (500, 2)).tolist() if a != b})
    edges = write_state(spark.createDataFrame(pairs, "src long, dst long"), "edges")
    ids = spark.range(100).select("id")  # the last ten have no link
    for min_block, damping, frac in ((0, 0.0, 0.4), (8, 0.3, 1.0)):
        one, other = (hf.fit_simple(edges, 6, frac, seed=3, stop=Stop(max_iter=6, tol=0.0, patience=9), ids=ids, min_block=min_block, damping=damping, backend=b) for b in ("task", "packed"))
        assert [(r[1], r[3], r[4]) for r in one.trace.rows] == [(r[1], r[3], r[4]) for r in other.trace.rows]
        assert sorted(map(tuple, one.labels.collect())) == sorted(map(tuple, other.labels.collect()))


def test_scaling_reads_edges_that_are_written(spark, sf, monkeypatch):
    seen = []
    monkeypatch.setattr(scaling, "scaling", lambda edges, run: seen.append(edges) or edges)
    workloads.workload_scaling(spark, sf)
    assert all("/state/edges-" in f for f in seen[0].inputFiles()) and "Join" not in plan_of(seen[0])


def test_all_labelings_are_released_together(spark, monkeypatch):
    rng = np.random.default_rng(6)
    pairs = sorted({(min(a, b), max(a, b)) for a, b in rng.integers(0, 60, (240, 2)).tolist() if a != b})
    edges = write_state(spark.createDataFrame(pairs, "src long, dst long"), "edges")
    written = []
    for module in (experiments, release):
        monkeypatch.setattr(module, "write_state", lambda df, label: written.append(label) or write_state(df, label))
    experiments.releases(spark, edges, (2,), 2, 2, 1, 5)
    few = [*written]
    written.clear()
    graphs, sets = experiments.releases(spark, edges, (2, 3, 5), 2, 2, 1, 5)
    assert written == few  # the driver plans one release, whatever the number of labelings
    assert [s[:2] for s in sets] == [(k, kind) for k in (2, 3, 5) for kind in ("optimised", "random")]
    labels = edges.selectExpr("src AS id").union(edges.selectExpr("dst")).distinct().selectExpr("id", "array(int(id % 3), int(id % 2 * 3)) AS labs")
    both = write_state(release.summaries(edges, labels, [3, 5]), "both")  # two blocks of the second stay empty
    drawn = release.expand(release.draw_counts(both, 2, 4), release.member_ranks(labels.selectExpr("id", "posexplode(labs) AS (graph, lab)")), 4).collect()
    for g, k in enumerate((3, 5)):
        own = labels.selectExpr("id", f"labs[{g}] AS lab")
        one = release.summary(edges, own, k)
        assert sorted(map(tuple, both.where(f"graph = {g}").drop("graph").collect())) == sorted(map(tuple, one.collect()))
        alone = release.expand(release.draw_counts(one, 2, 4), release.member_ranks(own), 4)
        assert sorted(tuple(r)[1:] for r in drawn if r["graph"] == g) == sorted(map(tuple, alone.collect()))
    assert graphs.where("run = 0").count() == len(pairs)


def test_pairs_are_drawn_in_blocks_as_one_by_one(spark, monkeypatch, tmp_path):
    monkeypatch.setattr(rng, "PAIRS_AT_ONCE", 50)
    monkeypatch.setattr(drawn, "RANGE", 20)
    keys = [-1000, -17, -9, -1, 0, 3, 3, None, *range(8, 13), *range(97, 105), 12345, 2**40, 2**62]
    for draw, keys in ((0.3, keys), (0.0, keys), (1.0, keys), (1.0, [None])):
        part = spark.createDataFrame([(k,) for k in keys], "p_partkey long")
        part.write.mode("overwrite").parquet(f"{tmp_path}/part.parquet")
        made = tables.planted_simple(spark, str(tmp_path), draw, draw / 4, 3)
        pairs = part.selectExpr("p_partkey AS src").join(part.selectExpr("p_partkey AS dst"), F.col("src") < F.col("dst"))
        chance = F.when(F.col("src") % 3 == F.col("dst") % 3, draw).otherwise(draw / 4)
        want = pairs.where(rng.portable(42, "p1", F.col("src"), F.col("dst")) < chance)
        assert sorted(map(tuple, made.collect())) == sorted(map(tuple, want.collect()))
        assert "md5" not in plan_of(made) and "MapInArrow" in plan_of(made)


def test_a_pair_of_blocks_is_hashed_in_slices(monkeypatch):
    seen, plain = [], rng._pair_heads
    monkeypatch.setattr(rng, "_pair_heads", lambda x, y: seen.append(len(x) * len(y)) or plain(x, y))
    ids = np.arange(95, 1095)
    found = {(int(i), int(j)): u for part in rng.pairs_under(1, "expand", ids, ids, 0.05) for i, j, u in zip(*part)}
    assert max(seen) <= rng.PAIRS_AT_ONCE and sum(seen) < 0.6 * 1000 * 1000
    assert 0.04 < len(found) / (1000 * 999 / 2) < 0.06
    assert all(u == rng.portable_texts(1, "expand", [f"{ids[i]}|{ids[j]}"])[0] for (i, j), u in list(found.items())[:500])


def test_degrees_of_the_releases_are_counted_once(spark, monkeypatch):
    edges = write_state(spark.createDataFrame([(k, (k * k + 1) % 30 + 30) for k in range(30)], "src long, dst long"), "edges")
    made = experiments.degree_distributions(spark, edges, (2,), 2, 2)
    assert all("/state/degrees-" in f for f in made.inputFiles()) and made.count() > 0
