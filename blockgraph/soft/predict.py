"""Predictions from a soft or hard fit: expected rating, existence, likeliest category, top-N unseen items."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.state import write_state


def mean_tensor(cat: DataFrame, values: DataFrame) -> DataFrame:
    """a, b, mean value of each block pair; values(c, value)."""
    return cat.join(F.broadcast(values), "c").groupBy("a", "b").agg(F.sum(F.col("p") * F.col("value")).alias("mean"))


def _flat(mean: DataFrame, value: str) -> DataFrame:
    """One row: flat matrix and its number of columns."""
    cells = F.array_sort(F.collect_list(F.struct("a", "b", F.col(value).alias("x"))))
    return mean.agg(F.transform(cells, lambda r: r["x"]).alias("matrix"), (F.max("b") + 1).alias("nb"))


def _bilinear(pairs: DataFrame, left: DataFrame, right: DataFrame, matrix: DataFrame, name: str) -> DataFrame:
    met = pairs.join(left.select(F.col("id").alias("src"), F.col("vec").alias("ml")), "src").join(right.select(F.col("id").alias("dst"), F.col("vec").alias("mr")), "dst").join(F.broadcast(matrix))
    inner = lambda a: F.aggregate(F.sequence(F.lit(0), F.size("mr") - 1), F.lit(0.0), lambda s, b: s + F.get("mr", b) * F.get("matrix", a * F.col("nb") + b))
    value = F.aggregate(F.sequence(F.lit(0), F.size("ml") - 1), F.lit(0.0), lambda s, a: s + F.get("ml", a) * inner(a))
    return met.withColumn(name, value).drop("ml", "mr", "matrix", "nb")


def soft(pairs: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, values: DataFrame) -> DataFrame:
    """pairs with pred, the expected value under the mixture, through the matrix of block-pair means."""
    return _bilinear(pairs, left, right, _flat(mean_tensor(cat, values), "mean"), "pred")


def exists(pairs: DataFrame, left: DataFrame, right: DataFrame, density: DataFrame) -> DataFrame:
    """pairs with pred, the probability of an edge; density(a, b, p)."""
    return _bilinear(pairs, left, right, _flat(density, "p"), "pred")


def hard(pairs: DataFrame, left: DataFrame, right: DataFrame, train: DataFrame) -> DataFrame:
    """pairs with pred, the mean training rating of the two blocks (of all edges where they share none).

    train(src, dst, value)."""
    ends = lambda df: df.join(left.select(F.col("id").alias("src"), F.col("lab").alias("a")), "src", "left").join(right.select(F.col("id").alias("dst"), F.col("lab").alias("b")), "dst", "left")
    means = ends(train).groupBy("a", "b").agg(F.avg("value").alias("mean"))
    overall = train.agg(F.avg("value").alias("overall"))
    return ends(pairs).join(F.broadcast(means), ["a", "b"], "left").join(F.broadcast(overall)).withColumn("pred", F.coalesce("mean", "overall")).drop("a", "b", "mean", "overall")


def dist(pairs: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame) -> DataFrame:
    """src, dst, c, p: the whole category distribution of each pair."""
    out = None
    categories = [r["c"] for r in cat.select("c").distinct().orderBy("c").collect()]
    for c in categories:
        part = _bilinear(pairs, left, right, _flat(cat.where(F.col("c") == c), "p"), "p").select("src", "dst", F.lit(c).alias("c"), "p")
        out = part if out is None else out.unionAll(part)
    return out


def mode(pairs: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame) -> DataFrame:
    """pairs with the likeliest category, the smallest among equals."""
    best = F.max_by("c", F.struct(F.round("p", 9), -F.col("c")))
    return dist(pairs, left, right, cat).groupBy("src", "dst").agg(best.alias("c"))


def top_n(train: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, values: DataFrame, n: int) -> DataFrame:
    """src, dst, rank, pred: the n unseen items of each user with the highest expected value.

    Users meet items by block of their likeliest membership first, so a user is scored against each item once.
    """
    users = left.select(F.col("id").alias("src"), F.lit(1).alias("k"))
    items = right.select(F.col("id").alias("dst"), F.lit(1).alias("k"))
    unseen = users.join(items, "k").drop("k").join(train.select("src", "dst"), ["src", "dst"], "left_anti")
    scored = soft(unseen, left, right, cat, values)
    order = W.partitionBy("src").orderBy(F.desc(F.round("pred", 9)), "dst")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= n).select("src", "dst", "rank", "pred")


def _best_of_tile(matrix: np.ndarray, n: int, rows: int = 256):
    """The n best unseen items of one block for each user of another; rows users are scored at a time."""

    def tile(table: pa.Table) -> pa.Table:
        users, items, seen = (table.filter(pc.equal(table.column("kind"), kind)) for kind in range(3))
        src, dst = users.column("x").to_numpy(), items.column("x").to_numpy()
        out = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        if len(src) and len(dst):
            vectors = lambda part: part.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(part), -1)
            ml, mr = vectors(users) @ matrix, vectors(items)
            by_user, by_item = np.argsort(src), np.argsort(dst)
            src, ml, dst, mr = src[by_user], ml[by_user], dst[by_item], mr[by_item]
            seen_at = np.searchsorted(src, seen.column("x").to_numpy()), np.searchsorted(dst, seen.column("y").to_numpy())
            for at in range(0, len(src), rows):
                pred = ml[at : at + rows] @ mr.T
                key = np.round(pred, 9)
                here = (seen_at[0] >= at) & (seen_at[0] < at + rows)
                key[seen_at[0][here] - at, seen_at[1][here]] = -np.inf
                k = min(n, len(dst))
                least = np.partition(key, len(dst) - k, axis=1)[:, len(dst) - k, None]
                u, v = np.nonzero((key >= least) & (key > -np.inf))  # the n best and all equal to the last
                order = np.lexsort((v, -key[u, v], u))
                u, v = u[order], v[order]
                first = np.arange(len(u)) - np.searchsorted(u, u) < n
                u, v = u[first], v[first]
                out = [np.concatenate(pair) for pair in zip(out, (src[at + u], dst[v], pred[u, v]))]
        return pa.table(dict(zip(("src", "dst", "pred"), out)))

    return tile


LEAF, BATCH = 512, 256


def _near_order(vec: np.ndarray, size: int) -> np.ndarray:
    """Rows in an order in which each run of `size` is close together: halved along the widest dimension."""
    order, todo = np.arange(len(vec)), [(0, len(vec))]
    while todo:
        at, upto = todo.pop()
        if upto - at > size:
            own = order[at:upto]
            wide = np.ptp(vec[own], axis=0).argmax()
            half = -(-(upto - at) // size) // 2 * size
            order[at:upto] = own[np.argpartition(vec[own, wide], half)]
            todo += [(at, at + half), (at + half, upto)]
    return order


def _turned(vec: np.ndarray) -> np.ndarray:
    """An orthonormal basis along the spread of the rows: bounds by dimension are narrow where rows don't differ, as in
    the direction of a membership's sum."""
    apart = vec - vec.mean(axis=0)
    return np.linalg.eigh(apart.T @ apart)[1]


def _frozen(**columns: np.ndarray) -> bytes:
    sink = pa.BufferOutputStream()
    table = pa.table(columns)
    with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


def _thawed(blob: pa.Scalar) -> list[np.ndarray]:
    return [c.to_numpy() for c in pa.ipc.open_stream(blob.as_buffer()).read_all().columns]


def _by_dimension(vec: np.ndarray) -> dict[str, np.ndarray]:
    return {f"v{k}": vec[:, k] for k in range(vec.shape[1])}


def _rows_of(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return flat.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def _item_packs(most: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Items (id, vec) as blobs of at most about `most` items, near ones together."""

    def packed(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(held)
        ids, vec = table.column("id").to_numpy(), _rows_of(table.column("vec"))
        by_id = np.argsort(ids)  # equal vectors in the order of their ids, whatever the order of arrival
        order = by_id[_near_order(vec[by_id] @ _turned(vec), LEAF)]
        return pa.RecordBatch.from_arrays([pa.array([_frozen(id=ids[order], **_by_dimension(vec[order]))], pa.binary())], ["items"])

    def packs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for batch in batches:
            held, rows = [*held, batch], rows + batch.num_rows
            if rows >= most:
                yield packed(held)
                held, rows = [], 0
        if rows:
            yield packed(held)

    return packs


def _user_pack(matrix: np.ndarray) -> Callable[[pa.Table], pa.Table]:
    """A block of users as one row: their ids and weights of the items' blocks, near ones together, and what they have seen."""

    def pack(table: pa.Table) -> pa.Table:
        users = table.filter(pc.is_null(table.column("y")))
        seen = table.filter(pc.is_valid(table.column("y")))
        if not len(users):
            return pa.table({"u": pa.array([], pa.int32()), "users": pa.array([], pa.binary()), "seen": pa.array([], pa.binary())})
        src, weight = users.column("x").to_numpy(), _rows_of(users.column("vec")) @ matrix
        order = _near_order(weight @ _turned(weight), BATCH)
        by_id = np.argsort(src[order])
        who = by_id[np.searchsorted(src[order], seen.column("x").to_numpy(), sorter=by_id)]
        what = seen.column("y").to_numpy()
        by_user = np.lexsort((what, who))
        blobs = _frozen(id=src[order], **_by_dimension(weight[order])), _frozen(who=who[by_user].astype(np.int32), what=what[by_user])
        return pa.table({"u": pa.array([table.column("u")[0].as_py()], pa.int32()), "users": pa.array([blobs[0]], pa.binary()), "seen": pa.array([blobs[1]], pa.binary())})

    return pack


class _Best:
    """The n best unseen items of each user of a block, over packs of items. A run of items is scored for those users only
    whose n-th best so far is not above what the run can reach."""

    def __init__(self, users: list[np.ndarray], seen: list[np.ndarray], n: int) -> None:
        self.src, self.weight = users[0], np.stack(users[1:], axis=1)
        self.who, self.what = seen
        self.n, shape = n, (len(self.src), n)
        self.key, self.pred, self.dst = np.full(shape, -np.inf), np.zeros(shape), np.full(shape, np.iinfo(np.int64).max)

    def meet(self, items: list[np.ndarray]) -> None:
        ids, vec = items[0], np.stack(items[1:], axis=1)
        runs = np.arange(0, len(ids), LEAF)
        basis = _turned(vec)
        low, high = (f.reduceat(vec @ basis, runs) for f in (np.minimum, np.maximum))
        for at in range(0, len(self.src), BATCH):
            own = slice(at, at + BATCH)
            w = self.weight[own]
            turned = w @ basis
            reach = np.maximum(turned, 0) @ high.T + np.minimum(turned, 0) @ low.T
            reach += 1e-8 + 1e-12 * np.abs(reach)  # scores are compared by nine digits
            most = reach.max(axis=0)
            seen = slice(*np.searchsorted(self.who, (at, at + len(w))))
            for run in np.argsort(-most, kind="stable"):
                if most[run] < self.key[own, -1].min():
                    break
                users = np.flatnonzero(reach[:, run] >= self.key[own, -1])
                if len(users):
                    here = slice(runs[run], runs[run] + LEAF)
                    self._add(at, users, w[users] @ vec[here].T, ids[here], seen)

    def _add(self, at: int, users: np.ndarray, pred: np.ndarray, ids: np.ndarray, seen: slice) -> None:
        key = np.round(pred, 9)
        by_id = np.argsort(ids)
        place = by_id[np.minimum(np.searchsorted(ids, self.what[seen], sorter=by_id), len(ids) - 1)]
        met = np.flatnonzero(ids[place] == self.what[seen])
        line = np.full(BATCH, -1)
        line[users] = np.arange(len(users))
        who = line[self.who[seen][met] - at]
        key[who[who >= 0], place[met][who >= 0]] = -np.inf
        least = self.key[at + users, -1]
        if len(ids) > self.n:  # the n best of the run and all equal to the last
            least = np.maximum(least, np.partition(key, len(ids) - self.n, axis=1)[:, len(ids) - self.n])
        row, v = np.nonzero((key >= least[:, None]) & (key > -np.inf))
        if not len(row):
            return
        rows = np.unique(row)
        held = at + users[rows]
        who = np.concatenate([np.searchsorted(rows, row), np.repeat(np.arange(len(rows)), self.n)])
        key, value, dst = (np.concatenate([new, old[held].ravel()]) for new, old in ((key[row, v], self.key), (pred[row, v], self.pred), (ids[v], self.dst)))
        order = np.lexsort((dst, -key, who))
        first = order[np.arange(len(order)) - np.searchsorted(who[order], who[order]) < self.n]
        self.key[held], self.pred[held], self.dst[held] = (x[first].reshape(-1, self.n) for x in (key, value, dst))

    def rows(self) -> pa.RecordBatch:
        u, k = np.nonzero(self.key > -np.inf)
        return pa.RecordBatch.from_pydict({"src": self.src[u], "dst": self.dst[u, k], "rank": pa.array(k + 1, pa.int32()), "pred": self.pred[u, k]})


def _best_over_packs(n: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, best = None, None
        for batch in batches:
            for number, users, seen, items in zip(batch.column("u").to_pylist(), *(batch.column(c) for c in ("users", "seen", "items"))):
                if number != now:
                    if best:
                        yield best.rows()
                    now, best = number, _Best(_thawed(users), _thawed(seen), n)
                best.meet(_thawed(items))
        if best:
            yield best.rows()

    return run


def top_n_all(train: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, values: DataFrame, n: int, block: int = 1 << 14, pack: int = 1 << 18) -> DataFrame:
    """top_n for many users: a block of users meets packs of items, which are read where they were written, so no vector is
    copied by a shuffle. Runs of near items that cannot reach a user's n best are passed over by their bounds. The ends of
    train are among left and right."""
    cells = mean_tensor(cat, values).collect()
    matrix = np.zeros((max(r["a"] for r in cells) + 1, max(r["b"] for r in cells) + 1))
    for r in cells:
        matrix[r["a"], r["b"]] = r["mean"]
    left, right = (write_state(df.select(F.col("id").cast("long").alias("id"), F.col("vec").cast("array<double>").alias("vec")), "members") for df in (left, right))
    blocks, packs = (max(1, math.ceil(side.count() / most)) for side, most in ((left, block), (right, pack)))
    place = lambda c: F.pmod(F.xxhash64(F.col(c).cast("long")), F.lit(blocks)).cast("int").alias("u")
    none = F.lit(None)
    users = left.select(place("id"), F.col("id").alias("x"), none.cast("long").alias("y"), "vec")
    seen = train.select(place("src"), F.col("src").cast("long").alias("x"), F.col("dst").cast("long").alias("y"), none.cast("array<double>").alias("vec"))
    held = users.unionAll(seen).groupBy("u").applyInArrow(_user_pack(matrix), "u int, users binary, seen binary")
    items = write_state(right.repartition(packs).mapInArrow(_item_packs(pack), "items binary"), "items")
    return held.crossJoin(items.coalesce(1).hint("shuffle_replicate_nl")).mapInArrow(_best_over_packs(n), "src long, dst long, rank int, pred double")
