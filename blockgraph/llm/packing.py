"""Conflict-constrained best-fit packing of documents into training sequences of fixed capacity.

A sequence (bin) holds at most one document of each source and at most one of each duplicate cluster. Documents are
placed by falling length. Open bins are kept by residual; each carries a bitmap of its sources and one of its
duplicate clusters. A document looks for the smallest residual that holds it and goes on to the next larger one, the
successor, until a bin has room and no conflict; so it gets the tightest compatible bin, the oldest among equals. If
there is none, it opens a bin. Parts of a document longer than the capacity fill bins of their own, its remainder is
placed like a document.

Shards of about `shard` documents, dealt by a hash of doc_id, are packed independently; only lengths, ids and marks
are in a task's memory, never texts, and a hot source or cluster is spread over all shards.

Defined results: a row with length null, 0 or less is not packed and gets a null bin; a null source or cluster conflicts
with nothing; repeated rows are packed each (they conflict if their cluster is equal); rows with a null doc_id are
packed too; other columns are ignored; an empty table gives an empty result; a very long text takes as many pieces as its
words ask for.
"""

from __future__ import annotations

import math
from bisect import bisect_left, insort
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import texts_of

CAPACITY = 2048
SHARD = 8192
SCHEMA = "doc_id long, piece int, length long, bin long, start long"


class Bins:
    """Open bins by residual; a bitset tells which residuals occur."""

    def __init__(self, capacity: int) -> None:
        self.capacity, self.occupied, self.opened = capacity, 0, 0
        self.levels: list[dict[int, list[int]]] = [{} for _ in range(capacity + 1)]  # source bitmap -> bins in order
        self.clusters: dict[int, int] = {}  # bin -> cluster bitmap

    def place(self, length: int, source: int, cluster: int) -> tuple[int, int]:
        """Bin and start of an item; source, cluster: bitmaps of one bit or none."""
        waiting = self.occupied >> length
        while waiting:
            low = waiting & -waiting
            residual = length + low.bit_length() - 1
            chosen = self._compatible(residual, source, cluster)
            if chosen is not None:
                sources, number = chosen
                self._take_out(residual, sources, number)
                self._put(residual - length, sources | source, number, cluster)
                return number, self.capacity - residual
            waiting ^= low
        number, self.opened = self.opened, self.opened + 1
        self._put(self.capacity - length, source, number, cluster)
        return number, 0

    def _compatible(self, residual: int, source: int, cluster: int) -> tuple[int, int] | None:
        found = None
        for sources, bins in self.levels[residual].items():
            if not sources & source:
                number = next((b for b in bins if not self.clusters.get(b, 0) & cluster), None)
                if number is not None and (found is None or number < found[1]):
                    found = sources, number
        return found

    def _take_out(self, residual: int, sources: int, number: int) -> None:
        bins = self.levels[residual][sources]
        del bins[bisect_left(bins, number)]
        if not bins:
            del self.levels[residual][sources]
            if not self.levels[residual]:
                self.occupied &= ~(1 << residual)

    def _put(self, residual: int, sources: int, number: int, cluster: int) -> None:
        insort(self.levels[residual].setdefault(sources, []), number)
        self.occupied |= 1 << residual
        if cluster:
            self.clusters[number] = self.clusters.get(number, 0) | cluster


def _bits(values: list) -> list[int]:
    """A bit for each value that occurs at least twice; none for null and for values without a rival."""
    times: dict = {}
    for v in values:
        times[v] = times.get(v, 0) + 1
    numbers = {v: 1 << k for k, v in enumerate(v for v, n in times.items() if n > 1 and v is not None)}
    return [numbers.get(v, 0) for v in values]


def pack_items(items: list[tuple[int, int, object, object]], capacity: int) -> list[tuple[int, int, int, int | None, int | None]]:
    """(item, piece, length, bin, start) for items (doc_id, length, source, cluster) in any order."""
    source, cluster = _bits([i[2] for i in items]), _bits([i[3] for i in items])
    bins, out, todo = Bins(capacity), [], []
    for k, (doc, length, *_) in enumerate(items):
        if not length or length < 0:
            out.append((k, 0, 0, None, None))
            continue
        full, left = divmod(length, capacity)
        pieces = [capacity] * full + [left] * (left > 0)
        todo += [(-size, doc is None, doc or 0, piece, k) for piece, size in enumerate(pieces)]
    for size, _, _, piece, k in sorted(todo):
        number, start = bins.place(-size, source[k], cluster[k])
        out.append((k, piece, -size, number, start))
    return out


def _pack_shard(capacity: int):
    def pack(shard: pa.Table) -> pa.Table:
        items = sorted(zip(*(shard.column(c).to_pylist() for c in ("doc_id", "length", "source", "cluster", "shard")), strict=True), key=lambda r: tuple((x is None, x) for x in r if x is None or not isinstance(x, str)) + tuple(str(x) for x in r))
        first = items[0][4] << 32 if items else 0
        rows = [(items[k][0], piece, size, None if number is None else first + number, start) for k, piece, size, number, start in pack_items([i[:4] for i in items], capacity)]
        columns = list(zip(*rows, strict=True)) or [()] * 5
        return pa.table([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "piece", "length", "bin", "start"])

    return pack


def pack(items: DataFrame, many: int, capacity: int = CAPACITY, shard: int = SHARD) -> DataFrame:
    """doc_id, piece, length, bin and start for items(doc_id, length, source, cluster), about `many` of them."""
    rows = items.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("length").cast("long").alias("length"), F.col("source").cast("string").alias("source"), F.col("cluster").cast("long").alias("cluster"))
    shards = max(1, math.ceil(many / shard))
    placed = rows.withColumn("shard", F.pmod(F.xxhash64("doc_id", "cluster", "length"), F.lit(shards)))
    return placed.groupBy("shard").applyInArrow(_pack_shard(capacity), SCHEMA)


def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        words = pa.array([len(t.split()) for t in texts_of(batch.column(1))], pa.int64())
        yield pa.RecordBatch.from_arrays([batch.column(0), words, batch.column(2), batch.column(3)], ["doc_id", "length", "source", "cluster"])


def measured(docs: DataFrame) -> DataFrame:
    """doc_id, length (words), source and cluster (a hash of the text) of docs(doc_id, text, source)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("source").cast("string").alias("source"), F.xxhash64("text").alias("cluster"))
    return rows.mapInArrow(_measure, "doc_id long, length long, source string, cluster long")


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, shard: int = SHARD) -> DataFrame:
    """Pack docs(doc_id, text, source) by number of words; equal texts form a duplicate cluster."""
    return pack(measured(docs), docs.count(), capacity, shard)
