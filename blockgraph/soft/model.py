"""State of a soft clustering and how it meets the edges."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..em.loop import Trace

EPS = 1e-300
WIDE = 400


@dataclass
class SoftFit:
    left: DataFrame
    right: DataFrame
    cat: DataFrame
    trace: Trace


def flat_tensor(cat: DataFrame) -> DataFrame:
    """One row: theta, p at (a * B + b) * C + c, with the sizes. Bounded by A * B * C, whatever the graph."""
    sizes = cat.agg((F.max("a") + 1).alias("na"), (F.max("b") + 1).alias("nb"), (F.max("c") + 1).alias("nc"))
    rows = cat.agg(F.transform(F.array_sort(F.collect_list(F.struct("a", "b", "c", "p"))), lambda r: r["p"]).alias("theta"))
    return rows.join(sizes)


def attach(edges: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame) -> DataFrame:
    """edges(src, dst, cat) with the memberships ml, mr and the tensor theta."""
    met = edges.join(left.select(F.col("id").alias("src"), F.col("vec").alias("ml")), "src").join(right.select(F.col("id").alias("dst"), F.col("vec").alias("mr")), "dst")
    return met.join(F.broadcast(flat_tensor(cat)))


def weights(ml: Column, mr: Column, theta: Column, na: int, nb: int, nc: int, category: Column) -> Column:
    """Joint weight of an edge and each block pair, at a * B + b."""
    return F.transform(
        F.sequence(F.lit(0), F.lit(na * nb - 1)),
        lambda k: F.get(ml, (k / nb).cast("int")) * F.get(mr, k % nb) * F.get(theta, k * nc + category),
    )


def total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda s, x: s + x)


def sizes_of(left: DataFrame, right: DataFrame, cat: DataFrame) -> tuple[int, int, int]:
    row = cat.agg(F.max("a"), F.max("b"), F.max("c")).first()
    return row[0] + 1, row[1] + 1, row[2] + 1


def entropy(edges: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, sizes: tuple[int, int, int] | None = None) -> DataFrame:
    """Negative log-likelihood of the observed categories."""
    na, nb, nc = sizes or sizes_of(left, right, cat)
    met = attach(edges, left, right, cat)
    p = total(weights(F.col("ml"), F.col("mr"), F.col("theta"), na, nb, nc, F.col("cat")))
    return met.agg(F.sum(-F.ln(F.greatest(p, F.lit(EPS)))).alias("entropy"))


def sampled_entropy(edges: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, share: float, seed: int) -> DataFrame:
    """entropy estimated from a hash sample of the edges, and its standard error."""
    from ..rng import fast

    na, nb, nc = sizes_of(left, right, cat)
    met = attach(edges.where(fast(seed, "entropy", F.col("src"), F.col("dst")) < share), left, right, cat)
    cost = -F.ln(F.greatest(total(weights(F.col("ml"), F.col("mr"), F.col("theta"), na, nb, nc, F.col("cat"))), F.lit(EPS)))
    return met.agg((F.sum(cost) / share).alias("entropy"), (F.sqrt(F.count("*")) * F.stddev_samp(cost) / share).alias("stderr"))


def responsibilities(edges: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame) -> DataFrame:
    """src, dst, a, b, resp: how each block pair explains each edge."""
    na, nb, nc = sizes_of(left, right, cat)
    met = attach(edges, left, right, cat).withColumn("w", weights(F.col("ml"), F.col("mr"), F.col("theta"), na, nb, nc, F.col("cat")))
    rows = met.select("src", "dst", F.greatest(total(F.col("w")), F.lit(EPS)).alias("p"), F.posexplode("w").alias("k", "w"))
    return rows.select("src", "dst", (F.col("k") / nb).cast("int").alias("a"), (F.col("k") % nb).alias("b"), (F.col("w") / F.col("p")).alias("resp"))


def one_hot(labels: DataFrame, n_blocks: int) -> DataFrame:
    return labels.select("id", F.transform(F.sequence(F.lit(0), F.lit(n_blocks - 1)), lambda a: F.when(a == F.col("lab"), 1.0).otherwise(0.0)).alias("vec"))


def harden(mem: DataFrame) -> DataFrame:
    """The likeliest block of each vertex, the smallest among equals."""
    return mem.select("id", (F.array_position("vec", F.array_max("vec")) - 1).cast("int").alias("lab"))


def neighbour_mean(shares: DataFrame, blocks: int) -> DataFrame:
    """id, vec: mean of the share vectors of each vertex's edges."""
    if blocks <= WIDE:
        sums = shares.groupBy("id").agg(F.count("*").alias("deg"), *[F.sum(F.get("share", F.lit(a))).alias(f"s{a}") for a in range(blocks)])
        return sums.select("id", F.array(*[F.col(f"s{a}") / F.col("deg") for a in range(blocks)]).alias("vec"))
    cells = shares.select("id", F.posexplode("share").alias("a", "x")).groupBy("id", "a").agg(F.avg("x").alias("x"))
    return cells.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("a", "x"))), lambda r: r["x"]).alias("vec"))


def fill_cold(mem: DataFrame, ids: DataFrame, blocks: int, cold: str = "uniform") -> DataFrame:
    """Memberships for all ids: those without a training edge get the uniform row or the mean row."""
    if cold == "uniform":
        default = F.array(*[F.lit(1.0 / blocks)] * blocks)
        return ids.select("id").join(mem, "id", "left").select("id", F.coalesce("vec", default).alias("vec"))
    mean = mem.agg(F.array(*[F.avg(F.get("vec", F.lit(a))) for a in range(blocks)]).alias("mean"))
    return ids.select("id").join(mem, "id", "left").join(F.broadcast(mean)).select("id", F.coalesce("vec", "mean").alias("vec"))


def tensor_from(mass: DataFrame, before: DataFrame, smoothing: float = 0.0) -> DataFrame:
    """a, b, c, p from responsibility mass(a, b, c, m); a pair without mass keeps its row."""
    met = before.join(F.broadcast(mass), ["a", "b", "c"], "left").withColumn("m", F.coalesce("m", F.lit(0.0)) + smoothing)
    sums = met.groupBy("a", "b").agg(F.sum("m").alias("all"))
    return met.join(F.broadcast(sums), ["a", "b"]).select("a", "b", "c", F.when(F.col("all") > 0, F.try_divide("m", "all")).otherwise(F.col("p")).alias("p"))
