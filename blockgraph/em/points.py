"""Hard and soft EM for unit-covariance Gaussians over points in R^d: k-means and its soft twin."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.state import drop_state, write_state
from ..rng import portable
from .loop import Fit, Stop, Trace


def squared(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)


def start_centres(points: DataFrame, k: int, seed: int) -> DataFrame:
    """a, centre: the k points with the smallest hash."""
    chosen = points.select("id", "vec", portable(seed, "centre", F.col("id")).alias("u")).orderBy("u", "id").limit(k)
    return chosen.select((F.row_number().over(W.orderBy("u", "id")) - 1).alias("a"), F.col("vec").alias("centre"))


def assign(points: DataFrame, centres: DataFrame) -> DataFrame:
    """id, vec, lab, d2: the nearest centre, the smallest label among equals. Centres are k rows and are broadcast."""
    met = points.join(F.broadcast(centres)).select("id", "vec", F.struct(F.round(squared(F.col("vec"), F.col("centre")), 9).alias("d2"), F.col("a").alias("lab")).alias("near"))
    best = met.groupBy("id").agg(F.min("near").alias("near"), F.any_value("vec").alias("vec"))
    return best.select("id", "vec", "near.lab", "near.d2")


def centres_of(assigned: DataFrame, before: DataFrame) -> DataFrame:
    """a, centre: means of the members; an empty block keeps its centre."""
    cells = assigned.select(F.col("lab").alias("a"), F.posexplode("vec").alias("j", "x")).groupBy("a", "j").agg(F.avg("x").alias("x"))
    means = cells.groupBy("a").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "x"))), lambda r: r["x"]).alias("mean"))
    return before.join(means, "a", "left").select("a", F.coalesce("mean", "centre").alias("centre"))


def gaussian_entropy(assigned: DataFrame) -> DataFrame:
    """Negative log-likelihood of points under their centre with unit covariance; assigned(vec, d2)."""
    return assigned.agg((F.sum("d2") / 2 + F.sum(F.size("vec")) / 2 * math.log(2 * math.pi)).alias("entropy"))


def kmeans(points: DataFrame, k: int, seed: int = 1, stop: Stop | None = None) -> Fit:
    stop, trace = stop or Stop(), Trace("kmeans")
    centres = write_state(start_centres(points, k, seed), "centres")
    assigned = write_state(assign(points, centres), "assigned")
    trace.add(gaussian_entropy(assigned).first()[0])
    while not stop.reached(trace.entropies, trace.elapsed()):
        new = write_state(centres_of(assigned, centres), "centres")
        drop_state(centres)
        drop_state(assigned)
        centres, assigned = new, write_state(assign(points, new), "assigned")
        trace.add(gaussian_entropy(assigned).first()[0])
    return Fit({"centres": centres, "labels": assigned.select("id", "lab")}, trace)


def soft_responsibilities(points: DataFrame, centres: DataFrame) -> DataFrame:
    """id, vec, a, resp under equal weights, by log-sum-exp."""
    met = points.join(F.broadcast(centres)).select("id", "vec", "a", (-squared(F.col("vec"), F.col("centre")) / 2).alias("l"))
    own = W.partitionBy("id")
    shifted = met.withColumn("e", F.exp(F.col("l") - F.max("l").over(own)))
    return shifted.select("id", "vec", "a", (F.col("e") / F.sum("e").over(own)).alias("resp"))


def soft_centres(resp: DataFrame) -> DataFrame:
    cells = resp.select("a", "resp", F.posexplode("vec").alias("j", "x")).groupBy("a", "j").agg((F.sum(F.col("resp") * F.col("x")) / F.sum("resp")).alias("x"))
    return cells.groupBy("a").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "x"))), lambda r: r["x"]).alias("centre"))


def soft_entropy(points: DataFrame, centres: DataFrame) -> DataFrame:
    """Negative log-likelihood of the equal-weight mixture."""
    met = points.join(F.broadcast(centres)).select("id", F.size("vec").alias("d"), (-squared(F.col("vec"), F.col("centre")) / 2).alias("l"))
    top = met.groupBy("id").agg(F.max("l").alias("top"), F.any_value("d").alias("d"), F.count("*").alias("k"))
    per = met.join(top.select("id", "top", "k"), "id").groupBy("id").agg(F.sum(F.exp(F.col("l") - F.col("top"))).alias("s"), F.any_value("top").alias("top"), F.any_value("d").alias("d"), F.any_value("k").alias("k"))
    return per.agg(F.sum(F.ln("k") - F.col("top") - F.ln("s") + F.col("d") / 2 * math.log(2 * math.pi)).alias("entropy"))


def soft_gaussian(points: DataFrame, k: int, seed: int = 1, stop: Stop | None = None) -> Fit:
    stop, trace = stop or Stop(), Trace("gaussian")
    centres = write_state(start_centres(points, k, seed), "centres")
    trace.add(soft_entropy(points, centres).first()[0])
    while not stop.reached(trace.entropies, trace.elapsed()):
        new = write_state(soft_centres(soft_responsibilities(points, centres)), "centres")
        drop_state(centres)
        centres = new
        trace.add(soft_entropy(points, centres).first()[0])
    return Fit({"centres": centres}, trace)


class KMeansProblem:
    """k-means as a problem for the generic hard loop: assignment is the expectation, means are the maximisation."""

    def __init__(self, points: DataFrame) -> None:
        self.points = points

    def expect(self, state: dict[str, DataFrame]) -> DataFrame:
        return assign(self.points, state["centres"])

    def maximise(self, state: dict[str, DataFrame], expected: DataFrame) -> dict[str, DataFrame]:
        return {"centres": write_state(centres_of(expected, state["centres"]), "centres")}

    def entropy(self, state: dict[str, DataFrame]) -> float:
        return gaussian_entropy(self.expect(state)).first()[0]
