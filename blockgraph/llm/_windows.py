"""Exact comparison of all fixed-length windows of all texts, by minimiser buckets.

A window is `length` consecutive units (words or bytes) of one text. The minimiser of a window is the smallest hash of
its runs of `seed` units. Consecutive windows with one minimiser value travel as one packed string to the bucket of
that value, so equal windows always meet, and a text costs about (length + run) / run times its size instead of
`length` times. Before the shuffle equal strings of a pack of texts become one entry with a count and the earliest
place, so a passage that a third of all texts share costs one entry per pack, not one per text.

Buckets and parts are as many as the bytes of the corpus ask for, so what one task holds at a time doesn't grow with it.
A minimiser whose strings would outgrow a bucket is crowded: crowded() estimates loads on every SAMPLE_ONE_IN-th document
and returns a bitmap of fixed size. A crowded minimiser's windows are dealt by more of their content: the offset of the
minimiser in the window falls into one of PARTS slices, the units that all windows of that slice share around the
minimiser are hashed, and (minimiser, slice, hash) takes the minimiser's place. All of that is a function of the window,
so equal windows still meet, and which minimisers count as crowded changes the dealing only, never the answer.

A bucket answers with the windows that stay: nothing is sent back for the rest, so answers are bounded by the distinct
content of the corpus however often a passage is repeated.

Rows are told apart by doc_id and a hash of the text. Rows with a null doc_id take no part; a null text is empty.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ._common import gram_hashes, mix, shuffle_partitions, sliding_min, text_key, texts_of, word_bounds, word_hashes

PACK_BYTES = 12 << 20
BUCKET_BYTES = 32 << 20
PART_BYTES = 16 << 20
CROWDED_BYTES = 24 << 20
SAMPLE_ONE_IN = 256
SLOTS = 1 << 26
PARTS = 8
RUN_LIMIT = 4096
SEGMENT = 1 << 20
_SPACES = bytes.maketrans(bytes(range(9, 14)), b" " * 5)


@dataclass(slots=True)
class Entry:
    """One distinct packed string of a bucket: its minimiser, earliest place, number of places, anchor and windows.

    anchor is where the minimising run of units starts in the string, -1 if it occurs more than once there.
    """

    text: bytes
    value: int
    place: tuple[int, int, int]
    count: int
    anchor: int
    n: int


@dataclass(frozen=True)
class Windows:
    """Which windows: length and seed in units, and whether a unit is a word or a byte."""

    length: int
    seed: int
    words: bool

    def units(self, text: bytes) -> tuple[bytes, np.ndarray, np.ndarray, np.ndarray]:
        """Canonical text, where each unit starts and ends in it, and the hash of each run of seed units."""
        if self.words:
            text = text.translate(_SPACES).strip(b" ")
            if b"  " in text:
                text = re.sub(b" +", b" ", text)
            data = np.frombuffer(text, np.uint8)
            starts, ends = word_bounds(data)
            return text, starts, ends, gram_hashes(word_hashes(data, starts, ends), self.seed)
        starts = np.arange(len(text))
        return text, starts, starts + 1, _byte_grams(np.frombuffer(text, np.uint8), self.seed)

    def strings(self, text: bytes, crowd: Crowd | None = None) -> Iterator[tuple[np.ndarray, list[bytes], np.ndarray, np.ndarray, np.ndarray]]:
        """Minimiser values, packed strings, first windows, anchors and numbers of windows of the runs of one text."""
        if len(text) < self.length * (2 if self.words else 1) - 1:
            return
        step = SEGMENT
        if self.words or len(text) <= step + self.length:
            yield from self._strings(text, 0, crowd)
            return
        for at in range(0, len(text) - self.length + 1, step):  # long texts by segments of windows
            yield from self._strings(text[at : at + step + self.length - 1], at, crowd)

    def _strings(self, text: bytes, shift: int, crowd: Crowd | None) -> Iterator[tuple[np.ndarray, list[bytes], np.ndarray, np.ndarray, np.ndarray]]:
        text, starts, ends, grams = self.units(text)
        if len(starts) < self.length:
            return
        reach = self.length - self.seed + 1
        least = sliding_min(grams, reach)
        cut = np.flatnonzero(least[1:] != least[:-1]) + 1
        first, last = np.append(0, cut), np.append(cut, len(least))  # last: exclusive
        if (last - first).max() > RUN_LIMIT:
            pieces = [(a, min(a + RUN_LIMIT, e)) for f, e in zip(first.tolist(), last.tolist(), strict=True) for a in range(f, e, RUN_LIMIT)]
            first, last = np.array(pieces).T
        values = least[first]
        seen = np.zeros(1 << 16, bool)
        seen[values & np.uint64(0xFFFF)] = True
        at = np.flatnonzero(seen[grams & np.uint64(0xFFFF)])
        ordered, candidates = np.sort(values), grams[at]
        at = at[ordered[np.minimum(np.searchsorted(ordered, candidates), len(ordered) - 1)] == candidates]
        if len(at) == len(values) and np.array_equal(grams[at], values):
            anchors = starts[at] - starts[first]
        else:
            anchors = np.array(self._anchors(grams, at, values, first, last, reach, starts))
        low, high = starts[first].tolist(), ends[last + self.length - 2].tolist()
        strings = [text[a:b] for a, b in zip(low, high, strict=True)]
        packed = crowd.holds(values) if crowd is not None else np.zeros(0, bool)
        if packed.any():
            stay = np.flatnonzero(~packed)
            yield values[stay], [strings[k] for k in stay.tolist()], first[stay] + shift, anchors[stay], (last - first)[stay]
            rows = [row for k in np.flatnonzero(packed).tolist() for row in self._apart(text, starts, ends, grams, values[k], int(first[k]), int(last[k]))]
            value, strings, begins, anchors, n = zip(*rows, strict=True)
            yield np.array(value, np.uint64), list(strings), np.array(begins) + shift, np.array(anchors), np.array(n)
        else:
            yield values, strings, first + shift, anchors, last - first

    def _apart(self, text: bytes, starts: np.ndarray, ends: np.ndarray, grams: np.ndarray, value: np.uint64, first: int, last: int) -> Iterator[tuple[int, bytes, int, int, int]]:
        """The run of windows first .. last - 1 of a crowded minimiser, by slices of the minimiser's offset: value of
        slice and shared units, string, first window, anchor and number of windows of each part."""
        reach = self.length - self.seed + 1
        width = max(1, math.ceil(reach / PARTS))
        found = np.flatnonzero(grams[first : last + reach - 1] == value) + first
        windows = np.arange(first, last)
        at = found[np.searchsorted(found, windows)]  # the leftmost place of the minimiser in each window
        slices = (at - windows) // width
        cut = np.flatnonzero((np.diff(at, prepend=-1) != 0) | (np.diff(slices, prepend=-1) != 0))
        for a, e in zip(cut.tolist(), [*cut[1:].tolist(), len(windows)], strict=True):
            anchor, part = int(at[a]), int(slices[a])
            low, high = anchor - part * width, anchor - min(part * width + width, reach) + 1 + self.length
            mark = hashlib.blake2b(text[starts[low] : ends[high - 1]], digest_size=8, key=value.tobytes() + bytes([part]))
            begin, end = first + a, first + e
            once = np.searchsorted(found, end + reach - 1) - np.searchsorted(found, begin) == 1
            yield int.from_bytes(mark.digest(), "little"), text[starts[begin] : ends[end + self.length - 2]], begin, int(starts[anchor] - starts[begin]) if once else -1, end - begin

    def _anchors(self, grams, at, values, first, last, reach, starts) -> list[int]:
        places: dict[int, list[int]] = {}
        for value, p in zip(grams[at].tolist(), at.tolist(), strict=True):
            places.setdefault(value, []).append(p)
        arrays = {v: np.array(p) for v, p in places.items()}
        out = []
        for value, f, e in zip(values.tolist(), first.tolist(), last.tolist(), strict=True):
            p = arrays[value]
            lo, hi = np.searchsorted(p, (f, e + reach - 1))
            out.append(int(starts[p[lo]] - starts[f]) if hi - lo == 1 else -1)
        return out


@dataclass(frozen=True)
class Crowd:
    """Crowded minimisers as a bitmap over the low bits of their values."""

    bits: np.ndarray

    def holds(self, values: np.ndarray) -> np.ndarray:
        slot = (values & np.uint64(SLOTS - 1)).astype(np.int64)
        return (self.bits[slot >> 3] >> (slot & 7).astype(np.uint8)) & 1 > 0


def _loads(windows: Windows) -> Callable:
    def loads(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for pack in _packs(batch):
                runs = [r for *_, text in pack for r in windows.strings(text)]
                if runs:
                    slot, inverse = np.unique(np.concatenate([r[0] for r in runs]) & np.uint64(SLOTS - 1), return_inverse=True)
                    load = np.bincount(inverse, [len(s) for r in runs for s in r[1]])
                    yield pa.RecordBatch.from_arrays([pa.array(slot.astype(np.int64)), pa.array(load.astype(np.int64))], ["slot", "load"])

    return loads


def crowded(spark: SparkSession, rows: DataFrame, windows: Windows) -> Crowd | None:
    """Minimisers whose strings add up to more than CROWDED_BYTES, by a sample of rows(doc_id, key, text); None if there
    are none. The bitmap has SLOTS bits (8 MB), whatever the corpus."""
    sample = rows.where(F.pmod(F.xxhash64("doc_id", "key"), F.lit(SAMPLE_ONE_IN)) == 0)
    loads = sample.mapInArrow(_loads(windows), "slot long, load long").groupBy("slot").agg(F.sum("load").alias("load"))
    heavy = loads.where(F.col("load") * SAMPLE_ONE_IN > CROWDED_BYTES).select((F.col("slot") + 1).alias("slot"))  # bitmap functions count from 1
    pieces = heavy.groupBy(F.bitmap_bucket_number("slot").alias("k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("slot")).alias("bits")).collect()
    if not pieces:
        return None
    bits = np.zeros(SLOTS // 8, np.uint8)
    for r in pieces:
        piece = np.frombuffer(r["bits"], np.uint8)
        bits[(r["k"] - 1) * len(piece) : r["k"] * len(piece)] = piece
    return Crowd(bits)


def _byte_grams(data: np.ndarray, seed: int) -> np.ndarray:
    """Hash of each run of seed bytes, seed a multiple of 8."""
    n = len(data) - seed + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    eight, raw = np.empty(len(data) - 7, np.uint64), data.tobytes()
    for j in range(min(8, len(eight))):
        eight[j::8] = np.frombuffer(raw, np.uint64, (len(raw) - j) // 8, j)
    out = mix(eight[:n])
    for j in range(8, seed, 8):
        out = mix(out * np.uint64(0x9E3779B97F4A7C15) + eight[j : j + n])
    return out


COLUMNS = (("value", np.uint64), ("doc", np.int64), ("key", np.int64), ("first", np.int64), ("anchor", np.int32), ("count", np.int32), ("n", np.int32), ("size", np.int32))


def _joined(arrays: list[np.ndarray], parts: list[bytes]) -> bytes:
    return b"".join([len(arrays[0]).to_bytes(8, "little"), *(a.tobytes() for a in arrays), *parts])


def _split(blob: bytes, kinds: list) -> tuple[list[np.ndarray], int]:
    n, at, arrays = int.from_bytes(blob[:8], "little"), 8, []
    for kind in kinds:
        arrays.append(np.frombuffer(blob, kind, n, at))
        at += n * np.dtype(kind).itemsize
    return arrays, at


def _dealt(names: list[str], parts: np.ndarray, blob_of: Callable[[np.ndarray], bytes], level: int) -> pa.RecordBatch:
    """One row (part, size, blob) for each part that occurs; blob_of gets the row numbers of a part in order."""
    order = np.argsort(parts, kind="stable")
    cut = np.flatnonzero(np.diff(parts[order], prepend=-1))
    blobs = [blob_of(rows) for rows in np.split(order, cut[1:])] if len(order) else []
    codec = pa.Codec("zstd", level)
    return pa.RecordBatch.from_arrays([pa.array(parts[order[cut]], pa.int32()), pa.array([len(b) for b in blobs], pa.int64()), pa.array([codec.compress(b, asbytes=True) for b in blobs], pa.binary())], names)


def _opened(blobs: pa.Table) -> Iterator[bytes]:
    codec = pa.Codec("zstd")
    for size, blob in zip(blobs.column("size").to_pylist(), blobs.column("blob"), strict=True):
        yield codec.decompress(blob.as_buffer(), size, asbytes=True)


def _packs(batch: pa.RecordBatch) -> Iterator[list[tuple[int, int, bytes]]]:
    """Rows of a batch in packs of bounded bytes, each in order of doc_id and key."""
    pack, held = [], 0
    for doc, key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), texts_of(batch.column(2)), strict=True):
        pack.append((doc, key, text))
        held += len(text)
        if held >= PACK_BYTES:
            yield sorted(pack)
            pack, held = [], 0
    if pack:
        yield sorted(pack)


def _part_of(doc: np.ndarray, key: np.ndarray, parts: int) -> np.ndarray:
    return (mix(doc.astype(np.int64).view(np.uint64) ^ mix(key.astype(np.int64).view(np.uint64))) % np.uint64(parts)).astype(np.int32)


def _send(windows: Windows, buckets: int, shared) -> Callable:
    """shared: a broadcast Crowd, or None."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        crowd = shared.value if shared is not None else None
        for batch in batches:
            for pack in _packs(batch):
                found = [(k, *runs) for k, (_, _, text) in enumerate(pack) for runs in windows.strings(text, crowd) if len(runs[0])]
                if not found:
                    continue
                row = np.repeat([f[0] for f in found], [len(f[1]) for f in found])
                texts = [s for f in found for s in f[2]]
                value, first, anchor, n = (np.concatenate([f[i] for f in found]) for i in (1, 3, 4, 5))
                del found
                earliest = dict(zip(reversed(texts), range(len(texts) - 1, -1, -1), strict=True))
                keep = np.sort(np.fromiter(earliest.values(), np.int64, len(earliest)))
                count = np.ones(len(texts), np.int64)
                if len(keep) < len(texts):
                    for s, times in Counter(texts).items():
                        count[earliest[s]] = times
                doc, key = np.array([p[0] for p in pack], np.int64), np.array([p[1] for p in pack], np.int64)
                columns = {"value": value, "doc": doc[row], "key": key[row], "first": first, "anchor": anchor, "count": count, "n": n}

                def blob_of(rows: np.ndarray) -> bytes:
                    own = keep[rows]
                    parts = [texts[k] for k in own.tolist()]
                    columns["size"] = np.array([len(s) for s in parts])
                    return _joined([(columns[c] if c == "size" else columns[c][own]).astype(kind) for c, kind in COLUMNS], parts)

                bucket = ((value[keep] >> np.uint64(20)) % np.uint64(buckets)).astype(np.int32)
                yield _dealt(["bucket", "size", "blob"], bucket, blob_of, 3)

    return send


Judge = Callable[[list[list[Entry]]], list[list[np.ndarray]]]
ANSWER = (np.int64, np.int64, np.int64, np.int32, np.int32)


def _settle(judge: Judge, most: int, parts: int) -> Callable:
    """What a bucket does. judge: which windows of each entry stay, for groups of entries with one minimiser; the only
    entry of a minimiser stays whole, where its anchor shows that its windows differ, if it has at most `most` places."""

    def settle(blobs: pa.Table) -> pa.Table:
        columns: dict[str, list] = {c: [] for c, _ in COLUMNS}
        held, where = [], []
        for blob in _opened(blobs):
            arrays, at = _split(blob, [kind for _, kind in COLUMNS])
            for (c, _), a in zip(COLUMNS, arrays, strict=True):
                columns[c].append(a)
            where.append(at + np.cumsum(arrays[-1], dtype=np.int64) - arrays[-1])
            held.append(blob)
        whole = {c: np.concatenate(a) for c, a in columns.items()}
        start, source = np.concatenate(where), np.repeat(np.arange(len(held)), [len(w) for w in where])
        _, inverse, times = np.unique(whole["value"], return_inverse=True, return_counts=True)
        lone = (times[inverse] == 1) & (whole["anchor"] >= 0)
        known: dict[bytes, Entry] = {}
        rows = np.flatnonzero(~lone)
        picked = [whole[c][rows].tolist() for c, _ in COLUMNS]
        for value, doc, key, first, anchor, count, n, size, at, k in zip(*picked, start[rows].tolist(), source[rows].tolist(), strict=True):
            new = Entry(held[k][at : at + size], value, (doc, key, first), count, anchor, n)
            entry = known.setdefault(new.text, new)
            if entry is not new:
                entry.count += new.count
                entry.place = min(entry.place, new.place)
        del held
        groups: dict[int, list[Entry]] = {}
        for entry in known.values():
            groups.setdefault(entry.value, []).append(entry)
        said: list[tuple[int, int, int, int, bytes]] = []
        contested = []
        for group in groups.values():
            if len(group) > 1 or group[0].anchor < 0:
                contested.append(group)
            elif group[0].count <= most:
                said.append((*group[0].place, group[0].n, b""))
        for group, answers in zip(contested, judge(contested), strict=True):
            for entry, stays in zip(group, answers, strict=True):
                if stays.any():
                    said.append((*entry.place, entry.n, b"" if stays.all() else np.packbits(stays).tobytes()))
        alone = np.flatnonzero(lone & (whole["count"] <= most))
        more = list(zip(*said, strict=True)) or [()] * 5
        doc, key, first, n = (np.concatenate((whole[c][alone], np.array(m, np.int64))) for c, m in zip(("doc", "key", "first", "n"), more, strict=False))
        masks = more[4]

        def blob_of(own: np.ndarray) -> bytes:
            tail = [masks[k] for k in (own[own >= len(alone)] - len(alone)).tolist()]
            sizes = np.zeros(len(own), np.int64)
            sizes[own >= len(alone)] = [len(m) for m in tail]
            return _joined([a.astype(kind) for a, kind in zip((doc[own], key[own], first[own], n[own], sizes), ANSWER, strict=True)], tail)

        return pa.Table.from_batches([_dealt(["part", "size", "blob"], _part_of(doc, key, parts), blob_of, 3)])

    return settle


def _pack_texts(parts: int) -> Callable:
    def pack_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for pack in _packs(batch):
                doc, key = np.array([p[0] for p in pack], np.int64), np.array([p[1] for p in pack], np.int64)
                sizes = np.array([len(p[2]) for p in pack], np.int64)

                def blob_of(own: np.ndarray) -> bytes:
                    return _joined([doc[own], key[own], sizes[own]], [pack[k][2] for k in own.tolist()])

                yield _dealt(["part", "size", "blob"], _part_of(doc, key, parts), blob_of, 3)

    return pack_texts


def _apply(strike: Callable[[bytes, Callable[[int], np.ndarray]], tuple], schema: pa.Schema, length: int) -> Callable:
    def apply(texts: pa.Table, answers: pa.Table) -> pa.Table:
        columns: list[list[np.ndarray]] = [[], [], [], [], []]
        masks: list[bytes] = []
        for blob in _opened(answers):
            arrays, at = _split(blob, list(ANSWER))
            for column, a in zip(columns, arrays, strict=True):
                column.append(a)
            masks += [blob[e - s : e] for e, s in zip((at + np.cumsum(arrays[4], dtype=np.int64)).tolist(), arrays[4].tolist(), strict=True)]
        doc, key, first, n, size = (np.concatenate(c) if c else np.zeros(0, np.int64) for c in columns)
        order = np.lexsort((key, doc))
        doc, key, first, n, size = doc[order], key[order], first[order], n[order].astype(np.int64), size[order]
        rows = []
        for blob in _opened(texts):
            (docs, keys, sizes), at = _split(blob, [np.int64, np.int64, np.int64])
            low, high = np.searchsorted(doc, docs), np.searchsorted(doc, docs, "right")
            for d, k, s, a, e in zip(docs.tolist(), keys.tolist(), sizes.tolist(), low.tolist(), high.tolist(), strict=True):
                own = np.arange(a, e)
                own = own[key[a:e] == k]

                def removed(units: int, own: np.ndarray = own) -> np.ndarray:
                    return removed_units(units, length, first[own], n[own], [masks[j] if size[o] else b"" for j, o in zip(order[own].tolist(), own.tolist(), strict=True)] if size[own].any() else None)

                rows.append((d, *strike(blob[at : at + s], removed)))
                at += s
        return pa.table([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)] if rows else [pa.array([], f.type) for f in schema], schema=schema)

    return apply


def without_repeats(docs: DataFrame, windows: Windows, judge: Judge, most: int, strike: Callable, schema: pa.Schema, ddl: str) -> DataFrame:
    """strike(text, removed) for each row of docs(doc_id, text), after doc_id; removed(number of units) flags the units
    that some window covers which doesn't stay."""
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(F.col("text")).alias("key"), F.coalesce("text", F.lit("")).alias("text")).where(F.col("doc_id").isNotNull())
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(shuffle_partitions(spark), math.ceil(size / PART_BYTES))
    buckets = max(shuffle_partitions(spark), math.ceil(4 * size / BUCKET_BYTES))  # packed strings take up to four times the text
    crowd = crowded(spark, rows, windows)
    shared = spark.sparkContext.broadcast(crowd) if crowd is not None else None
    sent = rows.mapInArrow(_send(windows, buckets, shared), "bucket int, size long, blob binary")
    said = sent.repartition(max(shuffle_partitions(spark), buckets // 2), "bucket").groupBy("bucket").applyInArrow(_settle(judge, most, parts), "part int, size long, blob binary")
    texts = rows.mapInArrow(_pack_texts(parts), "part int, size long, blob binary")
    tasks = max(shuffle_partitions(spark), parts // 2)
    texts, said = texts.repartition(tasks, "part"), said.repartition(tasks, "part")
    return texts.groupBy("part").cogroup(said.groupBy("part")).applyInArrow(_apply(strike, schema, windows.length), ddl)


def removed_units(units: int, length: int, first: np.ndarray, n: np.ndarray, masks: list[bytes] | None) -> np.ndarray:
    """Which units of a text some window covers that doesn't stay; first, n: runs of windows that stay, whole where
    masks has nothing for them."""
    windows = units - length + 1
    if windows <= 0:
        return np.zeros(units, bool)
    edge = np.zeros(windows + 1, np.int32)
    edge[first] += 1
    np.subtract.at(edge, first + n, 1)
    goes = np.cumsum(edge[:-1]) == 0
    for f, many, mask in zip(first.tolist(), n.tolist(), masks or (), strict=False):
        if mask:
            goes[f : f + many] = ~np.unpackbits(np.frombuffer(mask, np.uint8), count=many).astype(bool)
    if not goes.any():
        return np.zeros(units, bool)
    edge = np.zeros(units + 1, np.int32)
    edge[:windows] += goes
    edge[length : length + windows] -= goes
    return np.cumsum(edge[:-1]) > 0


def runs_of(flags: np.ndarray) -> tuple[list[int], list[int]]:
    """Start and end of each maximal run of set flags."""
    if not flags.any():
        return [], []
    edge = np.diff(np.concatenate(([0], flags.astype(np.int8), [0])))
    return np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist()


SPANS = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
SPANS_DDL = "array<struct<start:long,end:long>>"
