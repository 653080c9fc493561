"""The experiments as functions: rating fits under a budget, fraction variants, releases against block counts, costs.

Each returns rows ready for a report. Graphs come from blockgraph.sources; those that were reported for other graphs are
brought to the given tables by thinning the co-purchase graph, evenly (thinned) or with heavy-tailed degrees (g1_heavy).
Fits run side by side, one a task (see grid); releases and measures are distributed.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..anonymize import release
from ..em.loop import Stop
from ..graph import vertices
from ..hard.stats import pair_cost
from ..init import random_labels
from ..metrics import fit as mf
from ..metrics import graphs as mg
from ..plans.placement import by_rows
from ..plans.state import write_state
from ..rng import fast, portable
from ..sources import tables as t
from .grid import GraphRun, RatingRun, graph_fits, rating_curves

INTERNET = {"vertices": 26_475, "edges": 53_381, "blocks": 100, "rounds": 300}
COAUTHORS = {"vertices": 18_771, "edges": 198_050, "blocks": 300, "rounds": 150}


def thinned(edges: DataFrame, wanted: int, seed: int = 1) -> DataFrame:
    """About `wanted` edges, chosen by hash."""
    share = min(1.0, wanted / max(1, edges.count()))
    return edges.where(fast(seed, "thin", F.col("src"), F.col("dst")) < share).select("src", "dst")


def rating_graph(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    """src, dst, cat from 0, fold: the rating graph (g4) or ratings with planted blocks (p2)."""
    edges = t.g4_rating(spark, sf_dir) if graph == "g4" else t.planted_rating(spark, sf_dir)
    return write_state(mf.with_fold(edges.select("src", "dst", (F.col("cat") - 1).alias("cat"))), graph)


def named(spark: SparkSession, runs: list, **columns) -> DataFrame:
    """run and the columns, each a function of a run: small, one row a run."""
    rows = [(k, *[f(r) for f in columns.values()]) for k, r in enumerate(runs)]
    return F.broadcast(spark.createDataFrame(rows, ["run", *columns]).withColumn("run", F.col("run").cast("int")))


def rating(spark: SparkSession, sf_dir: str, graph: str = "p2", a: int = 10, b: int = 10, draws: tuple[int | None, ...] = (None, 10, 20, 30), rounds: int = 1000, budget_s: float | None = None, folds: tuple[int, ...] = (0, 1, 2, 3, 4), seed: int = 1, hard: bool = True, tol: float = 0.0) -> DataFrame:
    """method, fold, iter, elapsed_s, entropy (training), rmse (test) and moved after each round of exact (draws None),
    sampled and hard fits. Rounds, a time budget or a tolerance end a fit."""
    stop = Stop(max_iter=rounds, time_budget_s=budget_s, tol=tol, patience=3)
    runs = [RatingRun("exact" if d is None else "sampled", fold, a, b, d, seed=seed, stop=stop) for fold in folds for d in draws]
    runs += [RatingRun("hard", fold, a, b, seed=seed, stop=stop) for fold in folds if hard]
    curves = rating_curves(rating_graph(spark, sf_dir, graph), runs)
    return curves.join(named(spark, runs, method=lambda r: r.label, fold=lambda r: r.fold), "run").select("method", F.col("fold").cast("int").alias("fold"), "iter", "elapsed_s", "entropy", "rmse", "moved")


def final_rounds(curves: DataFrame) -> DataFrame:
    """method, folds, rounds, seconds, entropy and rmse: the last round of each fit, averaged over folds."""
    last = curves.groupBy("method", "fold").agg(F.max_by(F.struct("iter", "elapsed_s", "entropy", "rmse"), "iter").alias("l"))
    return last.groupBy("method").agg(F.count("*").alias("folds"), F.avg("l.iter").alias("rounds"), F.avg("l.elapsed_s").alias("seconds"), F.avg("l.entropy").alias("entropy"), F.avg("l.rmse").alias("rmse"))


def block_sweep(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (5, 10, 20, 40), rounds: int = 3, draws: tuple[int | None, ...] = (None, 10, 20, 30), graph: str = "g4") -> DataFrame:
    """blocks, method, seconds_a_round and the entropy after the rounds, as the number of blocks grows."""
    runs = [RatingRun("exact" if d is None else "sampled", 0, k, k, d, stop=Stop(max_iter=rounds, tol=0.0)) for k in sizes for d in draws]
    curves = rating_curves(rating_graph(spark, sf_dir, graph), runs)
    last = curves.groupBy("run").agg((F.max("elapsed_s") / F.max("iter")).alias("seconds_a_round"), F.max_by("entropy", "iter").alias("entropy"))
    return last.join(named(spark, runs, blocks=lambda r: r.a, method=lambda r: r.label), "run").select("blocks", "method", "seconds_a_round", "entropy")


def scaled(spark: SparkSession, sf_dir: str, published: dict, gamma: float, seed: int = 1) -> DataFrame:
    """The co-purchase graph of the given tables with heavy tails and as many edges a vertex as a published graph."""
    n = t.table(spark, sf_dir, "part").count()
    return write_state(t.g1_heavy(spark, sf_dir, round(published["edges"] * n / published["vertices"]), gamma, seed), "heavy")


def fraction(spark: SparkSession, edges: DataFrame, n_blocks: int, rounds: int, fracs: tuple[float, ...] = (0.1, 1.0), seed: int = 1, damping: float = 0.0) -> DataFrame:
    """frac, iter, elapsed_s, entropy and moved of each fit."""
    runs = [GraphRun(n_blocks, f, rounds, seed, damping=damping) for f in fracs]
    rows = graph_fits(edges, runs).where("iter IS NOT NULL")
    return rows.join(named(spark, runs, frac=lambda r: r.frac), "run").select("frac", "iter", "elapsed_s", "entropy", "moved")


def releases(spark: SparkSession, edges: DataFrame, block_counts: tuple[int, ...], replicas: int, rounds: int, seed: int, min_block: int) -> tuple[DataFrame, list[tuple]]:
    """Owner's views of all releases as graphs(run, src, dst), and for each set of runs (n_blocks, kind, entropy, smallest
    block, number of the first run). Run 0 is the original.

    All labelings are summarised, ranked and expanded together: the driver plans one release, not one a labeling.
    """
    runs = [GraphRun(k, rounds=rounds, seed=seed, min_block=min_block) for k in block_counts]
    fits = write_state(graph_fits(edges, runs), "fits")
    kinds = [(run.n_blocks, kind) for run in runs for kind in ("optimised", "random")]
    fitted = fits.where("id IS NOT NULL").groupBy("id").agg(*[F.max(F.when(F.col("run") == k, F.col("lab"))).alias(f"optimised{k}") for k in range(len(runs))])
    start = portable(seed, "label", F.col("id"))
    labs = F.array(*[c for k, run in enumerate(runs) for c in (F.col(f"optimised{k}"), F.floor(F.col("u") * run.n_blocks).cast("int"))])
    labels = by_rows(write_state(fitted.withColumn("u", start).select("id", labs.alias("labs")), "labels"))
    whole = write_state(release.summaries(edges, labels, [k for k, _ in kinds]), "summary")
    members = labels.select("id", F.posexplode("labs").alias("graph", "lab"))
    made = release.expand(release.draw_counts(whole, replicas, seed), write_state(release.member_ranks(members), "ranks"), seed)
    out = edges.select(F.lit(0).alias("run"), "src", "dst").unionAll(made.select((F.col("graph") * replicas + F.col("replica") + 1).cast("int").alias("run"), "src", "dst"))
    facts = whole.groupBy("graph").agg(F.sum(pair_cost(F.col("hit"), F.col("pairs") - F.col("hit"))).alias("entropy"), F.min(F.when((F.col("a") == F.col("b")) & (F.col("na") > 0), F.col("na"))).alias("smallest"))
    known = {r["graph"]: r for r in facts.collect()}  # a row a labeling
    sets = [(n, kind, known[g]["entropy"], known[g]["smallest"], 1 + g * replicas) for g, (n, kind) in enumerate(kinds)]
    return write_state(out, "releases"), sets


def _over_replicas(spark: SparkSession, found: DataFrame, sets: list[tuple], replicas: int, *keys: str) -> DataFrame:
    """n_blocks, kind, keys, mean, spread of value(run, keys, value) over the replicas of each set."""
    runs = [(0, 0, "original", 0)] + [(first + r, k, kind, smallest) for k, kind, _, smallest, first in sets for r in range(replicas)]
    place = F.broadcast(spark.createDataFrame(runs, "run int, n_blocks int, kind string, smallest_block long"))
    return found.join(place, "run").groupBy("n_blocks", "kind", "smallest_block", *keys).agg(F.avg("value").alias("mean"), F.coalesce(F.stddev_samp("value"), F.lit(0.0)).alias("spread"))


def anonymise(spark: SparkSession, edges: DataFrame, block_counts: tuple[int, ...] = (5, 10, 20, 50), replicas: int = 5, rounds: int = 150, seed: int = 1, sources: int = 16, min_block: int = 5) -> DataFrame:
    """n_blocks, kind (optimised, random, original), smallest_block, metric, mean and spread over the replicas.

    Metrics: entropy, gcc, apl (from `sources` vertices), reachable, edges, degree_ks and degree_l1 (distance of the degree
    distributions), shared (released edges that the original has). All releases share each distributed pass.
    """
    edges = write_state(edges.select("src", "dst"), "edges")
    graphs, sets = releases(spark, edges, block_counts, replicas, rounds, seed, min_block)
    found = mg.shapes(graphs, sources, seed)
    shares = write_state(degree_shares(graphs), "degrees")
    own = shares.where("run = 0").select("deg", F.col("value").alias("p"))
    runs = shares.select("run").distinct()
    levels = runs.join(F.broadcast(shares.select("deg").distinct())).join(shares, ["run", "deg"], "left").join(own, "deg", "left")  # runs x degrees, both few
    gaps = levels.select("run", "deg", F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("value", F.lit(0.0)).alias("q"))
    upto = mg.W.partitionBy("run").orderBy("deg").rowsBetween(mg.W.unboundedPreceding, mg.W.currentRow)
    far = gaps.select("run", F.sum(F.col("p") - F.col("q")).over(upto).alias("gap"), F.abs(F.col("p") - F.col("q")).alias("d")).groupBy("run").agg(F.max(F.abs("gap")).alias("degree_ks"), F.sum("d").alias("degree_l1"))
    pairs = graphs.join(by_rows(edges.withColumn("hit", F.lit(1))), ["src", "dst"], "left").groupBy("run").agg((F.count("hit") / F.count("*")).alias("shared"))
    more = far.join(pairs, "run").select("run", F.inline(F.array(*[F.struct(F.lit(c).alias("metric"), F.col(c).alias("value")) for c in ("degree_ks", "degree_l1", "shared")])))
    measured = _over_replicas(spark, found.unionAll(more), sets, replicas, "metric")
    entropy = spark.createDataFrame([(k, kind, smallest, "entropy", float(e), 0.0) for k, kind, e, smallest, _ in sets], measured.schema)
    return measured.unionAll(entropy)


def degree_shares(graphs: DataFrame) -> DataFrame:
    """run, deg, value: the share of the vertices with an edge that have each degree, in each of graphs(run, src, dst)."""
    ends = graphs.select("run", F.col("src").alias("id")).unionAll(graphs.select("run", F.col("dst").alias("id")))
    counts = ends.groupBy("run", "id").agg(F.count("*").alias("deg")).groupBy("run", "deg").agg(F.count("*").alias("n"))
    whole = counts.groupBy("run").agg(F.sum("n").alias("all"))
    return counts.join(whole, "run").select("run", "deg", (F.col("n") / F.col("all")).alias("value"))


def degree_distributions(spark: SparkSession, edges: DataFrame, block_counts: tuple[int, ...] = (5, 10, 20, 50), replicas: int = 5, rounds: int = 150, seed: int = 1, min_block: int = 5) -> DataFrame:
    """n_blocks, kind, smallest_block, deg, share and its spread over the replicas; a replica without a degree counts as 0."""
    edges = write_state(edges.select("src", "dst"), "edges")
    graphs, sets = releases(spark, edges, block_counts, replicas, rounds, seed, min_block)
    shares = write_state(degree_shares(graphs), "degrees")  # read twice
    place = [(first + r, first) for *_, first in sets for r in range(replicas)] + [(0, 0)]
    firsts = F.broadcast(spark.createDataFrame(place, "run int, first int"))
    known = shares.join(firsts, "run")
    levels = known.select("first", "deg").distinct().join(firsts, "first").join(shares, ["run", "deg"], "left").select("run", "deg", F.coalesce("value", F.lit(0.0)).alias("value"))
    return _over_replicas(spark, levels, sets, replicas, "deg").withColumnRenamed("mean", "share")


def expansion_cost(spark: SparkSession, sf_dir: str, counts: tuple[int, ...] = (200, 2000)) -> DataFrame:
    """n, method, seconds, edges: every pair decided on its own against drawing edge counts."""
    rows, edges = [], t.g1_copurchase(spark, sf_dir).select("src", "dst")
    for n in counts:
        own = write_state(edges.where((F.col("src") < n) & (F.col("dst") < n)), "edges")
        labels = write_state(random_labels(vertices(own), 4, 1), "labels")
        summary = write_state(release.summary(own, labels, 4), "summary")
        for method, build in (("pairwise", lambda: release.expand_pairwise(summary, labels, 1)), ("sparse", lambda: release.expand(release.draw_counts(summary, 1, 1), release.member_ranks(labels), 1))):
            began = time.monotonic()
            made = build().count()
            rows.append((n, method, time.monotonic() - began, made))
    return spark.createDataFrame(rows, "n int, method string, seconds double, edges long")
