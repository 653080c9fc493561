"""Rounds of soft clustering: the exact expectation over all block pairs, and its Monte-Carlo estimate."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..em.loop import Stop, Trace
from ..init import random_cat, random_mem
from ..plans.placement import grid, replicate_for_grid
from ..plans.state import drop_state, write_state
from ..rng import cumulative, draw_block, fast, portable
from .kernel import edge_entropy, edge_pass, new_tensor, sums_by
from .model import EPS, WIDE, SoftFit, attach, entropy, flat_tensor, neighbour_mean, tensor_from, total, weights


def _mass(shared: DataFrame, na: int, nb: int) -> DataFrame:
    """a, b, c, m from edges with `resp` (flat over block pairs) and cat."""
    pairs = na * nb
    if pairs <= WIDE:
        sums = shared.groupBy("cat").agg(*[F.sum(F.get("resp", F.lit(k))).alias(f"s{k}") for k in range(pairs)])
        cells = sums.select(F.col("cat").alias("c"), F.posexplode(F.array(*[F.col(f"s{k}") for k in range(pairs)])).alias("k", "m"))
    else:
        cells = shared.select(F.col("cat").alias("c"), F.posexplode("resp").alias("k", "x")).groupBy("c", "k").agg(F.sum("x").alias("m"))
    return cells.select((F.col("k") / nb).cast("int").alias("a"), (F.col("k") % nb).alias("b"), "c", "m")


def _shared(met: DataFrame, na: int, nb: int, nc: int) -> DataFrame:
    """Edges with responsibilities and the shares of both ends."""
    weighed = met.withColumn("w", weights(F.col("ml"), F.col("mr"), F.col("theta"), na, nb, nc, F.col("cat")))
    resp = weighed.select("src", "dst", "cat", F.transform("w", lambda w: w / F.greatest(total(F.col("w")), F.lit(EPS))).alias("resp"))
    left = F.transform(F.sequence(F.lit(0), F.lit(na - 1)), lambda a: total(F.slice("resp", a * nb + 1, nb)))
    right = F.transform(F.sequence(F.lit(0), F.lit(nb - 1)), lambda b: F.aggregate(F.sequence(F.lit(0), F.lit(na - 1)), F.lit(0.0), lambda s, a: s + F.get("resp", a * nb + b)))
    return resp.select("src", "dst", "cat", "resp", left.alias("sl"), right.alias("sr"))


def _ends(shared: DataFrame, bipartite: bool) -> tuple[DataFrame, DataFrame]:
    there = shared.select(F.col("src").alias("id"), F.col("sl").alias("share"))
    back = shared.select(F.col("dst").alias("id"), F.col("sr").alias("share"))
    if bipartite:
        return there, back
    both = there.unionAll(back)
    return both, both


def symmetric_mass(mass: DataFrame) -> DataFrame:
    """Mass of a block pair and of its transpose together: for undirected graphs on one vertex set."""
    turned = mass.select(F.col("b").alias("a"), F.col("a").alias("b"), "c", "m")
    return mass.unionAll(turned).groupBy("a", "b", "c").agg(F.sum("m").alias("m"))


def exact_step(edges: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, sizes: tuple[int, int, int], bipartite: bool = True, symmetric: bool = False, smoothing: float = 0.0) -> tuple[DataFrame, DataFrame, DataFrame]:
    """One exact round: new left and right memberships and tensor."""
    na, nb, nc = sizes
    shared = _shared(attach(edges, left, right, cat), na, nb, nc)
    there, back = _ends(shared, bipartite)
    mass = _mass(shared, na, nb)
    new_left = neighbour_mean(there, na)
    return new_left, neighbour_mean(back, nb) if bipartite else new_left, tensor_from(symmetric_mass(mass) if symmetric else mass, cat, smoothing)


def drawn_pairs(edges: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, sizes: tuple[int, int, int], draws: int, seed: int, round_: int, uniform: Callable[..., Column] = portable) -> DataFrame:
    """src, dst, cat, d: `draws` block pairs (a, b, x) drawn from both memberships, weighted by the tensor.

    Running sums are built once a vertex, in one pass; after the first join only the draws travel, not the vector; a
    draw is a binary search. Weights x add up to 1 an edge, so a block drawn twice counts twice; they have a floor, so
    they never all vanish.
    """
    na, nb, nc = sizes
    cl = left.select(F.col("id").alias("src"), cumulative(F.col("vec")).alias("cl"))
    cr = right.select(F.col("id").alias("dst"), cumulative(F.col("vec")).alias("cr"))

    def drawn(cum: str, purpose: str, blocks: int) -> Column:
        numbers = F.array(*[uniform(seed, purpose, round_, F.col("src"), F.col("dst"), t) for t in range(draws)])
        return F.transform(numbers, lambda u: draw_block(F.col(cum), u, blocks))

    with_left = edges.select("src", "dst", "cat").join(cl, "src").select("src", "dst", "cat", drawn("cl", "drawl", na).alias("dl"))
    with_both = with_left.join(cr, "dst").select("src", "dst", "cat", "dl", drawn("cr", "drawr", nb).alias("dr"))
    met = with_both.join(F.broadcast(flat_tensor(cat).select("theta")))
    weight = F.zip_with("dl", "dr", lambda a, b: F.struct(a.alias("a"), b.alias("b"), F.greatest(F.get("theta", (a * nb + b) * nc + F.col("cat")), F.lit(EPS)).alias("w")))
    weighed = met.select("src", "dst", "cat", weight.alias("d"))
    weighed = weighed.withColumn("all", F.aggregate("d", F.lit(0.0), lambda s, d: s + d["w"]))
    return weighed.select("src", "dst", "cat", F.transform("d", lambda d: F.struct(d["a"].alias("a"), d["b"].alias("b"), (d["w"] / F.col("all")).alias("x"))).alias("d"))


def _mean_of(sums: DataFrame, blocks: int) -> DataFrame:
    """id, vec from id, k, x: the shares of a vertex add up to its degree."""
    cells = sums.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("k", "x"))).alias("m"), F.sum("x").alias("deg"))
    return cells.select("id", F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda k: F.coalesce(F.try_element_at("m", k), F.lit(0.0)) / F.col("deg")).alias("vec"))


def sampled_step(edges: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, sizes: tuple[int, int, int], draws: int, seed: int, round_: int, bipartite: bool = True, symmetric: bool = False, smoothing: float = 0.0, uniform: Callable[..., Column] = portable) -> tuple[DataFrame, DataFrame, DataFrame]:
    """One Monte-Carlo round. Each draw gives three sparse shares (left block, right block, tensor cell), which are summed
    in one pass over the edges: O(draws) rows an edge before the map-side sums, whatever the number of blocks."""
    na, nb, nc = sizes
    pairs = drawn_pairs(edges, left, right, cat, sizes, draws, seed, round_, uniform)
    share = lambda kind, id_, k, d: F.struct(F.lit(kind).alias("kind"), id_.cast("long").alias("id"), k.cast("int").alias("k"), d["x"].alias("x"))
    rows = F.flatten(F.transform("d", lambda d: F.array(share(0, F.col("src"), d["a"], d), share(1 if bipartite else 0, F.col("dst"), d["b"], d), share(2, F.col("cat"), d["a"] * nb + d["b"], d))))
    sums = write_state(pairs.select(F.inline(rows)).groupBy("kind", "id", "k").agg(F.sum("x").alias("x")), "shares")
    cells = sums.where("kind = 2").select((F.col("k") / nb).cast("int").alias("a"), (F.col("k") % nb).alias("b"), F.col("id").cast("int").alias("c"), F.col("x").alias("m"))
    new_left = _mean_of(sums.where("kind = 0"), na)
    new_left._pass = sums
    return new_left, _mean_of(sums.where("kind = 1"), nb) if bipartite else new_left, tensor_from(symmetric_mass(cells) if symmetric else cells, cat, smoothing)


def _arrow_edges(na: int, nb: int, nc: int, theta: np.ndarray, draws: int | None, seed: int, round_: int):
    """Edge batches with both vectors -> one row of share sums for each vertex of the batch, and of tensor mass.

    kind 0: left vertex, 1: right vertex (vec: summed shares, n: edges), 2: tensor (id: c * A + a, vec: mass by b; the
    entropy rides as cost on its first row).
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tensor = theta.reshape(na, nb, nc)
        mass, cost, seen = np.zeros((nc, na, nb)), 0.0, False
        for batch in batches:
            seen = True
            src, dst, c = (batch.column(k).to_numpy() for k in range(3))
            sl, sr, part, more = edge_pass(src, dst, c, _vectors(batch, 3, na), _vectors(batch, 4, nb), tensor, draws, seed, round_)
            mass, cost = mass + part, cost + more
            for kind, ids, shares in ((0, src, sl), (1, dst, sr)):
                keys, where = np.unique(ids, return_inverse=True)
                yield _rows(kind, keys, sums_by(where, shares, len(keys)), np.bincount(where), np.zeros(len(keys)))
        if seen:
            rows = nc * na
            yield _rows(2, np.arange(rows), mass.reshape(rows, nb), np.zeros(rows, np.int64), np.where(np.arange(rows) == 0, cost, 0.0))

    return run


def _vectors(batch: pa.RecordBatch, column: int, size: int) -> np.ndarray:
    return batch.column(column).flatten().to_numpy().reshape(-1, size)


def _met(edges: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """src, dst, cat and both vectors, by two shuffled joins."""
    return edges.select("src", "dst", "cat").join(left.select(F.col("id").alias("src"), F.col("vec").alias("ml")), "src").join(right.select(F.col("id").alias("dst"), F.col("vec").alias("mr")), "dst").select("src", "dst", "cat", "ml", "mr")


SUMS = "kind int, id long, vec array<double>, n long, cost double"


def _pass(edges: DataFrame, left: DataFrame, right: DataFrame, theta: np.ndarray, sizes: tuple[int, int, int], draws: int | None, seed: int, round_: int, measure: bool = False) -> DataFrame:
    """Rows of SUMS for one pass over the edges; measure: only the entropy, on a row of kind 2.

    Edges that placement.grid() dealt stay where they are: each cell gets the vectors of its vertices.
    """
    na, nb, nc = sizes
    if not {"su", "sv"} <= set(edges.columns):
        work = _arrow_entropy(na, nb, nc, theta) if measure else _arrow_edges(na, nb, nc, theta, draws, seed, round_)
        return _met(edges, left, right).mapInArrow(work, SUMS)
    side = edges._grid_side
    sent = [replicate_for_grid(state.select("id", "vec"), side, "id", end).select("su", "sv", F.lit(kind).alias("kind"), "id", "vec") for kind, (state, end) in enumerate(((left, "src"), (right, "dst")))]
    cells = edges.select("su", "sv", "src", "dst", "cat").groupBy("su", "sv")
    return cells.cogroup(sent[0].unionAll(sent[1]).groupBy("su", "sv")).applyInArrow(_grid_cell(na, nb, nc, theta, draws, seed, round_, measure), SUMS)


def _grid_cell(na: int, nb: int, nc: int, theta: np.ndarray, draws: int | None, seed: int, round_: int, measure: bool):
    def cell(edges: pa.Table, states: pa.Table) -> pa.Table:
        src, dst, c = (edges.column(k).to_numpy() for k in ("src", "dst", "cat"))
        kind, ids = states.column("kind").to_numpy(), states.column("id").to_numpy()
        ends = []
        for which, (own, size) in enumerate(((src, na), (dst, nb))):
            here = np.flatnonzero(kind == which)
            vectors = states.column("vec").take(pa.array(here)).combine_chunks().flatten().to_numpy().reshape(-1, size)
            order = np.argsort(ids[here], kind="stable")
            ends.append(vectors[order[np.searchsorted(ids[here][order], own)]])
        batch = pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst), pa.array(c), _lists(ends[0]), _lists(ends[1])], ["src", "dst", "cat", "ml", "mr"])
        work = _arrow_entropy(na, nb, nc, theta) if measure else _arrow_edges(na, nb, nc, theta, draws, seed, round_)
        return pa.Table.from_batches(list(work(iter([batch]))))

    return cell


def _arrow_entropy(na: int, nb: int, nc: int, theta: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cost = sum(edge_entropy(b.column(2).to_numpy(), _vectors(b, 3, na), _vectors(b, 4, nb), theta.reshape(na, nb, nc)) for b in batches)
        yield _rows(2, np.zeros(1, np.int64), np.zeros((1, 1)), np.zeros(1, np.int64), np.array([float(cost)]))

    return run


def arrow_entropy(edges: DataFrame, left: DataFrame, right: DataFrame, theta: np.ndarray, sizes: tuple[int, int, int]) -> float:
    return _pass(edges, left, right, theta, sizes, None, 0, 0, measure=True).agg(F.sum("cost")).first()[0] or 0.0


def _lists(vectors: np.ndarray) -> pa.ListArray:
    offsets = pa.array(np.arange(len(vectors) + 1) * vectors.shape[1], pa.int32())
    return pa.ListArray.from_arrays(offsets, pa.array(np.ascontiguousarray(vectors).ravel()))


def _rows(kind: int, ids: np.ndarray, vectors: np.ndarray, n: np.ndarray, cost: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), kind, np.int32)), pa.array(ids.astype(np.int64)), _lists(vectors), pa.array(n.astype(np.int64)), pa.array(cost)], ["kind", "id", "vec", "n", "cost"])


def arrow_step(edges: DataFrame, left: DataFrame, right: DataFrame, theta: np.ndarray, sizes: tuple[int, int, int], draws: int | None, seed: int = 1, round_: int = 1) -> tuple[DataFrame, DataFrame, np.ndarray, float]:
    """One round in numpy beside the joins: left, right, tensor, and the entropy before it (exact rounds only).

    draws None: the exact expectation by matrix products, O(A * B) a batch row without ever listing block pairs.
    Sums of a batch are sent, not edges, and meet by vertex.
    """
    na, nb, nc = sizes
    sent = _pass(edges, left, right, theta, sizes, draws, seed, round_)
    wide = max(na, nb)
    sums = sent.groupBy("kind", "id").agg(F.sum("n").alias("deg"), F.sum("cost").alias("cost"), *[F.sum(F.get("vec", F.lit(k))).alias(f"s{k}") for k in range(wide)])
    share = lambda k: F.when(F.col("kind") < 2, F.try_divide(F.col(f"s{k}"), F.col("deg"))).otherwise(F.col(f"s{k}"))
    state = write_state(sums.select("kind", "id", "cost", F.array(*[share(k) for k in range(wide)]).alias("vec")), "mem")
    parts = state.where("kind = 2").orderBy("id").select("vec", "cost").toPandas()  # A * C rows
    mass = (np.array([v[:nb] for v in parts["vec"]], float) if len(parts) else np.zeros((nc * na, nb))).reshape(nc, na, nb)
    new = new_tensor(mass, theta.reshape(na, nb, nc))
    pick = lambda kind, size: state.where(F.col("kind") == kind).select("id", F.slice("vec", 1, size).alias("vec"))
    out = pick(0, na), pick(1, nb), new.ravel(), float(parts["cost"].sum())
    out[0]._state_path = getattr(state, "_state_path", None)
    return out


def starts(edges: DataFrame, sizes: tuple[int, int, int], seed: int, bipartite: bool = True) -> tuple[DataFrame, DataFrame, DataFrame]:
    na, nb, nc = sizes
    cat = random_cat(edges.sparkSession, na, nb, nc, seed)
    if not bipartite:
        from ..graph import vertices

        mem = random_mem(vertices(edges), na, seed, "l")
        return mem, mem, cat
    left = random_mem(edges.select(F.col("src").alias("id")).distinct(), na, seed, "l")
    return left, random_mem(edges.select(F.col("dst").alias("id")).distinct(), nb, seed, "r"), cat


def _fit(edges: DataFrame, sizes: tuple[int, int, int], seed: int, stop: Stop, step: Callable, bipartite: bool, run_id: str, eval_every: int) -> SoftFit:
    trace = Trace(run_id)
    left, right, cat = (write_state(x, "soft") for x in starts(edges, sizes, seed, bipartite))
    if not bipartite:
        right = left
    trace.add(entropy(edges, left, right, cat, sizes).first()[0])
    number = 0
    while not stop.reached(trace.entropies, trace.elapsed()) and number < stop.max_iter:
        number += 1
        new = step(edges, left, right, cat, number)
        new_left, new_cat = write_state(new[0], "soft"), write_state(new[2], "soft")
        new_right = write_state(new[1], "soft") if bipartite else new_left
        for old in (left, right, cat) if bipartite else (left, cat):
            drop_state(old)
        drop_state(getattr(new[0], "_pass", None))
        left, right, cat = new_left, new_right, new_cat
        if number % eval_every == 0:
            with trace.untimed():
                trace.add(entropy(edges, left, right, cat, sizes).first()[0])
    return SoftFit(left, right, cat, trace)


def fit_exact(edges: DataFrame, a_blocks: int, b_blocks: int, categories: int, seed: int = 1, stop: Stop | None = None, bipartite: bool = True, symmetric: bool = False) -> SoftFit:
    """Exact mixed EM from a random start; edges(src, dst, cat) with categories 0 .. categories - 1."""
    sizes = (a_blocks, b_blocks, categories)
    return _fit(edges, sizes, seed, stop or Stop(max_iter=20), lambda e, left, right, cat, _: exact_step(e, left, right, cat, sizes, bipartite, symmetric), bipartite, "exact", 1)


def fit_sampled(edges: DataFrame, a_blocks: int, b_blocks: int, categories: int, draws: int | Callable[[int], int] = 20, seed: int = 1, stop: Stop | None = None, bipartite: bool = True, symmetric: bool = False, eval_every: int = 1, uniform: Callable[..., Column] = fast) -> SoftFit:
    """Sampled mixed EM; draws may grow with the round."""
    sizes = (a_blocks, b_blocks, categories)

    def step(e: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, number: int):
        many = draws(number) if callable(draws) else draws
        return sampled_step(e, left, right, cat, sizes, many, seed, number, bipartite, symmetric, uniform=uniform)

    return _fit(edges, sizes, seed, stop or Stop(max_iter=20), step, bipartite, "sampled", eval_every)


def fit_arrow(edges: DataFrame, a_blocks: int, b_blocks: int, categories: int, draws: int | None = None, seed: int = 1, stop: Stop | None = None, grid_side: int = 0) -> SoftFit:
    """The bipartite fits with the numpy backend, sampled if draws are given. The entropy after each round is measured
    outside the time of the trace, so sampled fits stop by tolerance too. grid_side: deal the edges on a grid once, so that
    they stay and only vectors move, each to grid_side cells."""
    sizes, stop = (a_blocks, b_blocks, categories), stop or Stop(max_iter=20)
    left, right, cat = starts(edges, sizes, seed)
    left, right = write_state(left, "soft"), write_state(right, "soft")
    if grid_side:
        edges = grid(edges.select("src", "dst", "cat"), grid_side).persist()
        edges._grid_side = grid_side
    theta = np.array([r["p"] for r in cat.orderBy("a", "b", "c").collect()])
    trace = Trace("exact" if draws is None else f"sampled{draws}")
    with trace.untimed():
        trace.add(arrow_entropy(edges, left, right, theta, sizes))
    while not stop.reached(trace.entropies, trace.elapsed()):
        new_left, new_right, theta, _ = arrow_step(edges, left, right, theta, sizes, draws, seed, len(trace.rows))
        drop_state(left)
        left, right = new_left, new_right
        with trace.untimed():
            trace.add(arrow_entropy(edges, left, right, theta, sizes))
    if grid_side:
        edges.unpersist()
    table = [(a, b, c, float(theta[(a * b_blocks + b) * categories + c])) for a in range(a_blocks) for b in range(b_blocks) for c in range(categories)]
    return SoftFit(left, right, edges.sparkSession.createDataFrame(table, "a int, b int, c int, p double"), trace)


def fit_auto(edges: DataFrame, a_blocks: int, b_blocks: int, categories: int, draws: int = 20, **more) -> SoftFit:
    """Exact where it touches fewer cells than sampling draws, sampled else."""
    if a_blocks * b_blocks <= a_blocks + draws * np.log2(max(2, a_blocks)) * 4:
        return fit_exact(edges, a_blocks, b_blocks, categories, **more)
    return fit_sampled(edges, a_blocks, b_blocks, categories, draws, **more)
