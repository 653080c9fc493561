"""The experiments at sizes that a query run can bear; blockgraph.eval.workloads takes any."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..eval import workloads as w
from ..plans.state import write_state
from ..sources import tables as t
from .base import query


BUDGET_S = 4.0


@query()
def workload_rating_curves(spark, sf_dir):
    """Entropy and test error against seconds: exact and sampled (10, 20, 30 draws) fits of planted ratings, 10 + 10
    blocks, five folds, a time budget a fit."""
    return w.rating(spark, sf_dir, "p2", 10, 10, (None, 10, 20, 30), budget_s=BUDGET_S, hard=False)


@query()
def workload_rating(spark, sf_dir):
    """The same at the end of the budget, averaged over the folds."""
    return w.final_rounds(w.rating(spark, sf_dir, "p2", 10, 10, (None, 10, 20, 30), budget_s=BUDGET_S, hard=False))


@query()
def workload_rating_given(spark, sf_dir):
    """The same on the given ratings, which have no structure: fits lower the entropy, not the RMSE."""
    return w.final_rounds(w.rating(spark, sf_dir, "g4", 10, 10, (None, 10, 20, 30), budget_s=BUDGET_S, hard=False))


@query()
def workload_soft_hard_curves(spark, sf_dir):
    """Sampled (30 draws) and hard fits with 15 + 15 blocks, five folds: entropy and test error after each round."""
    return w.rating(spark, sf_dir, "p2", 15, 15, (30,), rounds=60, budget_s=3 * BUDGET_S, tol=1e-5)


@query()
def workload_soft_hard(spark, sf_dir):
    """The same at the end: rounds, seconds, entropy, RMSE."""
    return w.final_rounds(w.rating(spark, sf_dir, "p2", 15, 15, (30,), rounds=60, budget_s=3 * BUDGET_S, tol=1e-5))


@query()
def workload_block_sweep(spark, sf_dir):
    """Seconds a round of exact and sampled fits at 5, 10, 20 and 40 blocks a side."""
    return w.block_sweep(spark, sf_dir, (5, 10, 20, 40), 2)


@query()
def workload_fraction_sparse(spark, sf_dir):
    """Traces with fractions 0.1 and 1.0, 100 blocks, 300 rounds, on a sparse heavy-tailed graph."""
    return w.fraction(spark, w.scaled(spark, sf_dir, w.INTERNET, 0.8), w.INTERNET["blocks"], w.INTERNET["rounds"])


@query()
def workload_fraction_dense(spark, sf_dir):
    """The same with 300 blocks, 150 rounds, on a denser graph."""
    return w.fraction(spark, w.scaled(spark, sf_dir, w.COAUTHORS, 0.6), w.COAUTHORS["blocks"], w.COAUTHORS["rounds"])


BLOCK_COUNTS = (5, 10, 20, 50)


@query()
def workload_anonymise(spark, sf_dir):
    """Entropy, path length, clustering coefficient, degree distance and overlap of five releases at each of four block
    counts, from optimised and from random blocks, on the sparse graph."""
    return w.anonymise(spark, w.scaled(spark, sf_dir, w.INTERNET, 0.8), BLOCK_COUNTS)


@query()
def workload_anonymise_dense(spark, sf_dir):
    return w.anonymise(spark, w.scaled(spark, sf_dir, w.COAUTHORS, 0.6), BLOCK_COUNTS)


@query()
def workload_degrees(spark, sf_dir):
    """Degree distributions of the same releases beside the original's."""
    return w.degree_distributions(spark, w.scaled(spark, sf_dir, w.INTERNET, 0.8), BLOCK_COUNTS)


@query()
def workload_expansion_cost(spark, sf_dir):
    return w.expansion_cost(spark, sf_dir, (200, 2000))


@query()
def workload_scaling(spark, sf_dir):
    """Seconds of one table-scored round at 1, 2 and 4 tasks."""
    from ..eval.scaling import scaling
    from ..graph import vertices
    from ..hard.fit import one_round
    from ..init import random_labels

    edges = write_state(t.g1_copurchase(spark, sf_dir).select("src", "dst"), "edges")  # built once, not for each number of tasks
    labels = write_state(random_labels(vertices(edges), 4, 1), "labels")
    return scaling(edges, lambda e: one_round(e, labels, 4, 0.3, "table", 1, 1).write.format("noop").mode("overwrite").save())


@query()
def state_size(spark, sf_dir):
    """Bytes of the soft and the hard state of the rating graph."""
    from ..eval.scaling import state_bytes
    from ..init import random_labels
    from ..soft.steps import starts

    edges = write_state(t.g4_rating(spark, sf_dir).select("src", "dst", (F.col("cat") - 1).alias("cat")), "edges")
    left, right, _ = starts(edges, (10, 10, 5), 1)
    hard = [random_labels(edges.select(F.col(c).alias("id")).distinct(), 10, 1) for c in ("src", "dst")]
    rows = [("soft", sum(map(state_bytes, (left, right)))), ("hard", sum(map(state_bytes, hard)))]
    return spark.createDataFrame(rows, "kind string, bytes long")
