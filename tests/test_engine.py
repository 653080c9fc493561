import numpy as np
import pytest
from pyspark.sql import functions as F

from blockgraph import init
from blockgraph.anonymize import release
from blockgraph.em import points as ep
from blockgraph.em.loop import Stop, Trace, multi_start
from blockgraph.functions import scalar
from blockgraph.graph import canonical, validate_edges, vertices
from blockgraph.hard import fit as hf
from blockgraph.hard import kernel, score, stats
from blockgraph.metrics import graphs as mg
from blockgraph.metrics import privacy as mp
from blockgraph.plans import placement
from blockgraph.plans.state import write_state
from blockgraph.queries.hard import TOY_EDGES, toy
from blockgraph.rng import alias_arrays, alias_table, decimals, draw_alias, fast, numpy_uniform, portable, portable_numpy, portable_texts
from blockgraph.soft import model, steps
from blockgraph.sources import edges as se
from blockgraph.sources import tables as t

TOY = kernel.Graph(6, np.array([a for a, _ in TOY_EDGES]), np.array([b for _, b in TOY_EDGES]))


def labels(text):
    return np.array([int(c) for c in text])


@pytest.mark.parametrize(("lab", "entropy"), [("000000", 10.363849639707), ("000111", 3.139488862587), ("010101", 10.001739199145), ("000011", 8.317766166719)])
def test_toy_entropies(spark, lab, entropy):
    edges, frame = toy(spark, labels(lab).tolist())
    assert abs(TOY.entropy(labels(lab), 2) - entropy) < 1e-9
    assert abs(hf.entropy_of(edges, frame, 2) - entropy) < 1e-9


def test_global_optimum_of_the_toy():
    best, lab = kernel.brute_force(TOY, 2)
    assert abs(best - 3.139488862587) < 1e-9 and lab in ((0, 0, 0, 1, 1, 1), (1, 1, 1, 0, 0, 0))


@pytest.mark.parametrize(("before", "after"), [("000011", "000111"), ("010101", "101010"), ("001111", "000111"), ("000111", "000111")])
def test_table_choices_on_the_toy(spark, before, after):
    edges, frame = toy(spark, labels(before).tolist())
    new = hf.one_round(edges, frame, 2, 1.0, "table", 1, 1).orderBy("id").collect()
    assert "".join(str(r["lab"]) for r in new) == after
    *_, (lab, _, _) = kernel.rounds(TOY, labels(before), 2, 1.0, 1, 1)
    assert "".join(map(str, lab)) == after


def test_full_batch_oscillates():
    states = ["".join(map(str, lab)) for lab, _, _ in kernel.rounds(TOY, labels("010101"), 2, 1.0, 4, 1)]
    assert states == ["101010", "010101"] * 2


def test_exact_scores_are_true_changes(spark):
    for lab in ("000111", "000011", "011010"):
        edges, frame = toy(spark, labels(lab).tolist())
        scores = score.score_exact(stats.vertex_links(edges, frame), frame, stats.block_pairs(edges, frame, 2)).collect()
        own = {r["id"]: r["score"] for r in scores if r["a"] == r["y"]}
        for r in scores:
            moved = labels(lab)
            moved[r["id"]] = r["a"]
            assert abs(r["score"] - own[r["id"]] - (TOY.entropy(moved, 2) - TOY.entropy(labels(lab), 2))) < 1e-9


def test_certificate_and_polish(spark):
    edges, frame = toy(spark)
    assert hf.local_optimality(edges, frame, 2).first()["locally_optimal"]
    edges, frame = toy(spark, [0, 0, 0, 0, 1, 1])
    assert not hf.local_optimality(edges, frame, 2).first()["locally_optimal"]
    lab, moves = kernel.polish(TOY, labels("000011"), 2)
    assert "".join(map(str, lab)) == "000111" and moves == 1


@pytest.fixture(scope="module")
def planted(spark, sf):
    return write_state(t.planted_simple(spark, sf, 0.25, 0.02, 4), "p1")


def noisy(planted, noise=0.4):
    u = portable(5, "noise", F.col("id"))
    return vertices(planted).select("id", F.when(u < noise, F.floor(portable(6, "noise", F.col("id")) * 4)).otherwise(F.col("id") % 4).cast("int").alias("lab"))


@pytest.mark.parametrize("backend", ["task", "frames"])
def test_planted_blocks_return_from_noise(planted, backend):
    start = write_state(noisy(planted), "start")
    fit = hf.fit_simple(planted, 4, 0.3, start=start, stop=Stop(max_iter=12, tol=0), backend=backend)
    truth = vertices(planted).select("id", (F.col("id") % 4).cast("int").alias("lab"))
    assert mp.nmi(fit.labels, truth).first()["nmi"] > 0.8 > mp.nmi(start, truth).first()["nmi"]
    assert fit.trace.entropies[-1] < 1.02 * hf.entropy_of(planted, truth, 4)
    assert mp.ari(truth, truth).first()["ari"] == 1.0


@pytest.mark.parametrize("frac", [0.3, lambda number: 0.5 if number < 3 else 0.2])
def test_backends_give_equal_labels(planted, frac):
    start = write_state(noisy(planted), "start")
    for stop in (Stop(max_iter=4, tol=0), Stop(max_iter=6, tol=0.05, patience=2)):
        local, frames = (hf.fit_simple(planted, 4, frac, seed=9, start=start, stop=stop, backend=b) for b in ("task", "frames"))
        assert sorted(map(tuple, local.labels.collect())) == sorted(map(tuple, frames.labels.collect()))
        assert [r[4] for r in local.trace.rows] == [r[4] for r in frames.trace.rows]
        assert np.allclose(local.trace.entropies, frames.trace.entropies, rtol=1e-9)


def test_scorers_agree_with_exact_on_planted(planted):
    start = write_state(noisy(planted), "start")
    st, links = stats.block_pairs(planted, start, 4), write_state(stats.vertex_links(planted, start), "links")
    moves = {k: {r["id"]: r["lab"] for r in score.best_moves(f(links, start, st)).collect()} for k, f in score.SCORERS.items()}
    agree = lambda k: np.mean([moves[k][v] == moves["exact"][v] for v in moves["exact"]])
    assert agree("table") >= 0.95 and agree("plugin") >= 0.85


def test_min_block_is_kept(planted):
    start = init.balanced_labels(vertices(planted), 4, 1)
    fit = hf.fit_simple(planted, 4, 0.5, start=start, stop=Stop(max_iter=3), min_block=45, backend="frames")
    assert mp.anonymity_level(fit.labels).first()["level"] >= 45
    merged = release.merge_until(planted, noisy(planted).withColumn("lab", F.when(F.col("id") < 5, 3).when(F.col("lab") == 3, 2).otherwise(F.col("lab")).cast("int")), 4, 20)
    assert mp.anonymity_level(merged).first()["level"] >= 20


def test_hub_statistics_sum_up(planted):
    lab = init.random_labels(vertices(planted), 4, 3)
    st = stats.block_pairs(planted, lab, 5).agg(F.sum("hit").alias("hit"), F.sum("pairs").alias("pairs")).first()
    n = vertices(planted).count()
    assert st["hit"] == planted.count() and st["pairs"] == n * (n - 1) / 2


def one_edge(spark):
    edges = spark.createDataFrame([(0, 1, 0)], "src long, dst long, cat int")
    left = spark.createDataFrame([(0, [0.75, 0.25])], "id long, vec array<double>")
    right = spark.createDataFrame([(1, [0.4, 0.6])], "id long, vec array<double>")
    p = [0.9, 0.2, 0.3, 0.5]
    cat = spark.createDataFrame([(k // 2, k % 2, c, x if c == 0 else 1 - x) for k, x in enumerate(p) for c in range(2)], "a int, b int, c int, p double")
    return edges, left, right, cat


def test_one_rated_edge(spark):
    state = one_edge(spark)
    assert abs(model.entropy(*state).first()[0] - 0.765717873395) < 1e-9
    resp = [r["resp"] for r in model.responsibilities(*state).orderBy("a", "b").collect()]
    assert np.allclose(resp, [0.580645, 0.193548, 0.064516, 0.161290], atol=1e-6)
    from blockgraph.soft import predict

    values = spark.createDataFrame([(0, 1.0), (1, 2.0)], "c int, value double")
    edges, left, right, cat = state
    assert abs(predict.soft(edges.select("src", "dst"), left, right, cat, values).first()["pred"] - 1.535) < 1e-9


@pytest.fixture(scope="module")
def ratings(spark, sf):
    return write_state(t.planted_rating(spark, sf).select("src", "dst", (F.col("cat") - 1).alias("cat")), "p2")


def test_exact_rounds_never_raise_entropy(ratings):
    fit = steps.fit_exact(ratings, 3, 3, 5, 2, Stop(max_iter=4))
    assert all(a >= b - 1e-6 for a, b in zip(fit.trace.entropies, fit.trace.entropies[1:]))
    sums = fit.left.select(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x).alias("s")).agg(F.min("s"), F.max("s")).first()
    assert abs(sums[0] - 1) < 1e-9 and abs(sums[1] - 1) < 1e-9
    per = fit.cat.groupBy("a", "b").agg(F.sum("p").alias("s")).agg(F.min("s"), F.max("s")).first()
    assert abs(per[0] - 1) < 1e-9 and abs(per[1] - 1) < 1e-9


def test_backends_agree(ratings):
    one = steps.fit_exact(ratings, 3, 4, 5, 2, Stop(max_iter=2))
    two = steps.fit_arrow(ratings, 3, 4, 5, None, 2, Stop(max_iter=2))
    assert np.allclose(one.trace.entropies, two.trace.entropies, rtol=1e-9)
    pairs = one.left.join(two.left.withColumnRenamed("vec", "other"), "id").select(F.aggregate(F.zip_with("vec", "other", lambda a, b: F.abs(a - b)), F.lit(0.0), lambda s, x: s + x).alias("d"))
    assert pairs.agg(F.max("d")).first()[0] < 1e-9


def test_more_draws_come_closer_to_exact(ratings):
    sizes = (3, 3, 5)
    state = [write_state(x, "s") for x in steps.starts(ratings, sizes, 2)]
    exact = {r["id"]: np.array(r["vec"]) for r in steps.exact_step(ratings, *state, sizes)[0].collect()}
    gaps = []
    for draws in (2, 10, 60):
        got = steps.sampled_step(ratings, *state, sizes, draws, 1, 1, uniform=fast)[0].collect()
        gaps.append(np.mean([np.abs(exact[r["id"]] - np.array(r["vec"])).sum() for r in got]))
    assert gaps[0] > gaps[1] > gaps[2]


def test_results_do_not_depend_on_partitions(ratings):
    sizes = (2, 3, 5)
    state = [write_state(x, "s") for x in steps.starts(ratings, sizes, 2)]
    rows = lambda e: sorted((r["id"], tuple(np.round(r["vec"], 9))) for r in steps.sampled_step(e, *state, sizes, 4, 1, 1)[0].collect())
    assert rows(ratings) == rows(ratings.repartition(7, "dst"))


def test_one_hot_soft_equals_hard_entropy(spark, ratings):
    left = init.random_labels(ratings.select(F.col("src").alias("id")).distinct(), 3, 1)
    right = init.random_labels(ratings.select(F.col("dst").alias("id")).distinct(), 4, 2)
    cells = stats.labelled(ratings, left, right).groupBy("a", "b", F.col("cat").alias("c")).agg(F.count("*").alias("n"))
    best = cells.join(cells.groupBy("a", "b").agg(F.sum("n").alias("all")), ["a", "b"]).select("a", "b", "c", (F.col("n") / F.col("all")).alias("p"))
    soft = model.entropy(ratings, model.one_hot(left, 3), model.one_hot(right, 4), best, (3, 4, 5)).first()[0]
    assert abs(soft - stats.profile_rating_entropy(ratings, left, right).first()[0]) < 1e-6


def test_planted_ratings_are_learnt(spark, sf):
    from blockgraph.eval import workloads

    rows = {r["method"]: r for r in workloads.final_rounds(workloads.rating(spark, sf, "p2", 5, 5, (None, 20), rounds=12, folds=(0,))).collect()}
    assert set(rows) == {"exact", "sampled 20", "hard"} and all(r["rmse"] < 1.4 for k, r in rows.items() if k != "hard")


def test_release_has_drawn_counts_and_no_repeats(spark, planted):
    lab = write_state(init.random_labels(vertices(planted), 3, 1), "lab")
    summary = release.summary(planted, lab, 3)
    counts = write_state(release.draw_counts(summary, 3, 7), "counts")
    out = write_state(release.expand(counts, release.member_ranks(lab), 7), "out")
    assert out.count() == out.distinct().count() == counts.agg(F.sum("cnt")).first()[0]
    assert out.where("src >= dst").isEmpty()
    assert abs(out.count() / 3 - planted.count()) < 4 * np.sqrt(planted.count())


@pytest.mark.parametrize("size", [1, 2, 3, 10, 45, 100, 1000])
def test_feistel_permutes_and_unrank_lists_pairs(size):
    assert sorted(release.feistel(np.arange(size), size, (1, 2))) == list(range(size))
    n = size + 1
    i, j = release.unrank(np.arange(n * (n - 1) // 2), n)
    assert sorted(zip(i, j)) == [(a, b) for a in range(n) for b in range(a + 1, n)]


def test_paths_triangles_components(spark):
    edges, _ = toy(spark)
    assert abs(mg.average_path_length(edges).first()["apl"] - 1.8) < 1e-12
    row = mg.global_clustering(edges).first()
    assert (row["triangles"], row["wedges"], round(row["gcc"], 12)) == (2, 10, 0.6)
    two = edges.unionAll(spark.createDataFrame([(10, 11)], "src long, dst long"))
    assert {r["root"] for r in mg.connected_components(two).collect()} == {0, 10}
    assert mg.sketched_path_length(edges).orderBy(F.desc("hop")).first()["pairs"] == 36


def test_kmeans_lowers_its_entropy(spark, sf):
    pts = write_state(t.planted_points(spark, sf).select("id", "vec"), "p")
    fit = multi_start(lambda s: ep.kmeans(pts, 4, s, Stop(max_iter=3)), [1, 2])
    assert all(a >= b - 1e-6 for a, b in zip(fit.trace.entropies, fit.trace.entropies[1:]))


def test_generic_loop_runs_kmeans(spark, sf):
    from blockgraph.em.loop import run_hard_em

    pts = write_state(t.planted_points(spark, sf).select("id", "vec"), "p")
    own = ep.kmeans(pts, 3, 1, Stop(max_iter=2)).trace.entropies
    generic = run_hard_em(ep.KMeansProblem(pts), {"centres": write_state(ep.start_centres(pts, 3, 1), "c")}, Stop(max_iter=2)).trace.entropies
    assert np.allclose(own, generic)


def test_fit_auto_picks_by_cost(ratings):
    assert steps.fit_auto(ratings, 2, 2, 5, 20, stop=Stop(max_iter=1)).trace.run_id == "exact"
    assert steps.fit_auto(ratings, 12, 12, 5, 2, stop=Stop(max_iter=1)).trace.run_id == "sampled"


def test_draws_may_grow(ratings):
    fit = steps.fit_sampled(ratings, 2, 2, 5, lambda n: 2 * n, 1, Stop(max_iter=2))
    assert len(fit.trace.entropies) == 3


def test_draws_of_arrays_are_those_of_texts():
    ids = np.concatenate((np.arange(9000), np.random.default_rng(1).integers(-(2**63), 2**63 - 1, 500), [-(2**63), 2**63 - 1, -1]))
    for purpose in ("choose", "x" * 27, "x" * 28, "x" * 60):  # texts of one block of the hash and longer ones
        want = portable_texts(7, purpose, [f"12|{i}" for i in ids.tolist()])
        assert np.array_equal(portable_numpy(7, purpose, 12, ids), want) and np.array_equal(portable_numpy(7, purpose, 12, decimals(ids)), want)
    assert len(portable_numpy(7, "choose", 12, ids[:0])) == 0


def test_random_numbers(spark):
    row = spark.range(1).select(portable(5, "7").alias("u")).first()
    assert abs(row["u"] - 0.2224815922201402) < 1e-15
    u = numpy_uniform(1, np.arange(20000), 3)
    assert abs(u.mean() - 0.5) < 0.02 and 0 <= u.min() and u.max() < 1
    vec = np.array([0.1, 0.6, 0.3])
    keep, other = alias_arrays(vec)
    back = np.array([sum((keep[s] if s == k else 0) + ((1 - keep[s]) if other[s] == k else 0) for s in range(3)) / 3 for k in range(3)])
    assert np.allclose(back, vec)
    df = spark.range(4000).select(draw_alias(alias_table(F.array(*[F.lit(float(x)) for x in vec])), fast(1, "x", F.col("id"))).alias("k"))
    assert abs(df.where("k = 1").count() / 4000 - 0.6) < 0.04


def test_stop_and_trace(spark, tmp_path):
    assert Stop(tol=0.1, patience=2, max_iter=9).reached([5.0, 5.0, 5.0], 0) and not Stop(tol=0.1).reached([5.0, 1.0, 1.0], 0)
    assert Stop(max_iter=1).reached([1.0, 2.0], 0) and Stop(time_budget_s=1).reached([1.0], 2)
    trace = Trace("r")
    trace.add(2.0)
    trace.add(1.0, 5)
    trace.write(spark, str(tmp_path / "trace"))
    assert spark.read.parquet(str(tmp_path / "trace")).where("run_id = 'r' AND iter = 1").first()["moved"] == 5


def test_edges_in_and_out(spark, tmp_path):
    (tmp_path / "e.tsv").write_text("# note\n1\t2\n2\t1\n3\t3\n")
    (tmp_path / "e.txt").write_text("# note\n1 2\n\n4   5\n")
    edges = validate_edges(se.read_edges(spark, str(tmp_path / "e.tsv")))
    assert [tuple(r) for r in canonical(edges).collect()] == [(1, 2)]
    assert se.read_edges(spark, str(tmp_path / "e.txt"), "text").count() == 2
    se.write_edges(edges.withColumn("replica", F.lit(0)), str(tmp_path / "out"), "csv")
    assert (tmp_path / "out" / "replica=0").exists()
    for kind in ("json", "orc"):
        se.write_edges(edges, str(tmp_path / kind), kind)
        assert se.read_edges(spark, str(tmp_path / kind), kind).count() == 3
    with pytest.raises(ValueError):
        validate_edges(edges.drop("dst"))


def test_generator_source(spark):
    spark.dataSource.register(se.PlantedSource)
    graph = spark.read.format("planted_graph").option("n", 400).option("inside", 0.2).option("across", 0.01).load()
    inside = graph.where("src % 4 = dst % 4").count()
    assert graph.where("src >= dst").isEmpty() and abs(inside / (4 * 100 * 99 / 2) - 0.2) < 0.03


def test_sql_functions(spark):
    scalar.register(spark)
    row = spark.sql("SELECT xlogx(2) AS a, xlogx(0) AS z, pair_cost(1, 8) AS b, soft_predict(array(1D, 0D), array(0D, 1D), array(1D, 2D, 3D, 4D)) AS c").first()
    assert np.allclose([row["a"], row["z"], row["b"], row["c"]], [2 * np.log(2), 0, 3.139488862587, 2])
    assert spark.sql("SELECT count(DISTINCT i, j) AS n FROM draw_pairs(10, 20, 1)").first()["n"] == 20


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, sf, planted):
    from blockgraph.queries.registry import QUERIES

    scan = plan(QUERIES["scan_lineitem"](spark, sf))
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThanOrEqual(l_quantity,25.0)]" in scan and "ReadSchema: struct<l_partkey:bigint,l_quantity:double>" in scan
    assert "BroadcastHashJoin" in plan(QUERIES["join_broadcast_labels"](spark, sf)) and "SortMergeJoin" in plan(QUERIES["join_merge_mem"](spark, sf))
    assert "Cartesian" not in plan(stats.block_pairs(planted, noisy(planted), 4))
    df = spark.range(10).select(F.col("id"))
    assert "broadcast" in placement.small_or_shuffled(df, 10, 8)._jdf.queryExecution().logical().toString().lower()
    assert "broadcast" not in placement.small_or_shuffled(df, 1 << 40, 8)._jdf.queryExecution().logical().toString().lower()


def test_placement_helpers(spark, planted):
    dealt = placement.grid(planted, 3)
    assert dealt.count() == planted.count() and dealt.select("su", "sv").distinct().count() == 9
    mem = vertices(planted)
    assert placement.replicate_for_grid(mem, 3, "id", "src").count() == 3 * mem.count()
    hits = placement.salted_sum(planted.withColumn("x", F.lit(1)), ["src"], "x", F.col("dst"), 4)
    assert hits.agg(F.sum("x")).first()[0] == planted.count()
    assert 0 < mem.where(placement.bucket_sample(0.25, 16, 1, F.col("id"))).count() < mem.count()


def test_degenerate_graphs(spark):
    none = spark.createDataFrame([], "src long, dst long")
    lab = spark.createDataFrame([(0, 0), (1, 1)], "id long, lab int")
    assert hf.entropy_of(none, lab, 3) == 0.0
    full = spark.createDataFrame([(0, 1), (0, 2), (1, 2)], "src long, dst long")
    assert hf.entropy_of(full, vertices(full).withColumn("lab", F.lit(0)), 1) == 0.0
    assert mg.global_clustering(none).first()["gcc"] == 0.0
