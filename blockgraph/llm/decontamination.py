"""Benchmark decontamination: edit-distance search for benchmark items in whole texts.

A document holds an item if some passage of it is within `share` of the item's length in word edits (insertion, deletion,
replacement). Words are runs of letters and digits (ASCII punctuation and white space part them), A-Z lower-cased.

1. Seeds. An item of n words and e edits keeps at least ceil((n - e) / (e + 1)) words in a row, so a passage that holds
   it shares a run of that many words (at most SEED) with it. Only passages around shared runs go on; this drops nothing.
2. Embedding. Each such item-sized window, and each item, is walked at random by the CGK rule: at every step the current
   symbol is written and a random bit of (step, symbol) tells whether to go on to the next symbol. Edit distance becomes
   Hamming distance. Of REPEATS walks, each with its own bits, SAMPLES written symbols at random steps make a key; a
   window stays a candidate for its item if any of the keys agrees.
3. Verification. The exact edit distance between the item and the best passage around the window decides.

Items travel to the tasks in blocks of bounded bytes. Blocks go one after the other, with a scan of the documents and a
written result for each, so neither a task nor the driver holds more than a block. Documents need no shuffle: each is judged where it is read.

Defined results: null texts and items hold nothing; items without words never match; rows with a null doc_id or item_id
are left out; repeated rows are judged each and reported once; of several passages the closest, then earliest is
reported (among equals the earliest end, then the latest start); other columns are ignored; an empty table gives an
empty result. Very long texts are searched whole, their windows 2,048 at a time.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ._common import forget, gram_hashes, materialise, mix, texts_of, word_bounds, word_hashes

SHARE = 0.2
SEED = 4
REPEATS = 48
SAMPLES = 2
BLOCK_BYTES = 16 << 20
FOUND = "doc_id long, item_id long, start long, n_words long, distance long"
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
BREAKS = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])


def allowed_edits(words: int, share: float) -> int:
    return math.floor(words * share)


def seed_length(words: int, share: float) -> int:
    edits = allowed_edits(words, share)
    return min(SEED, math.ceil((words - edits) / (edits + 1)))


def symbols(text: bytes) -> np.ndarray:
    """A 64-bit symbol for each word of a text."""
    data = np.frombuffer(text.translate(_LOWER), np.uint8)
    return word_hashes(data, *word_bounds(data, BREAKS))


def sampled_steps(item_sizes: np.ndarray) -> np.ndarray:
    """windows x REPEATS x SAMPLES: the steps each walk is looked at, drawn by the size of the item."""
    key = np.arange(SAMPLES, dtype=np.uint64)[None, None, :] + (np.arange(REPEATS, dtype=np.uint64) << np.uint64(32))[None, :, None]
    draw = mix(key + (item_sizes.astype(np.uint64) << np.uint64(8))[:, None, None])
    return (draw % (2 * item_sizes).astype(np.uint64)[:, None, None]).astype(np.int64)


def embed(windows: np.ndarray, sizes: np.ndarray, steps: np.ndarray) -> np.ndarray:
    """What REPEATS CGK walks over each row of windows (its first `size` symbols) write at the given steps."""
    rows, at = np.arange(len(windows))[:, None], np.zeros(steps.shape[:2], np.int64)
    walk = np.arange(REPEATS, dtype=np.uint64)[None, :] << np.uint64(20)
    out = np.zeros(steps.shape, np.uint64)
    padded = np.concatenate((windows, np.zeros((len(windows), 1), np.uint64)), axis=1)
    padded[np.arange(windows.shape[1] + 1)[None, :] >= sizes[:, None]] = 0
    for step in range(int(steps.max(initial=0)) + 1):
        current = padded[rows, at]
        np.copyto(out, current[:, :, None], where=steps == step)
        at += (mix(current + (walk + np.uint64(step))) >> np.uint64(63)).astype(np.int64)
        np.minimum(at, windows.shape[1], out=at)
    return out


class Items:
    """Benchmark items of one block, ready for search: seeds in hash order, sampled embeddings of each walk."""

    def __init__(self, ids: list[int], texts: list[bytes], share: float) -> None:
        kept = [(i, s) for i, s in zip(ids, map(symbols, texts), strict=True) if len(s)]
        self.ids, self.words, self.share = [i for i, _ in kept], [s for _, s in kept], share
        self.edits = np.array([allowed_edits(len(s), share) for s in self.words], np.int64)
        self.sizes = np.array([len(s) for s in self.words], np.int64)
        self.seeds: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for k in sorted({seed_length(len(s), share) for s in self.words}):
            found = [(gram_hashes(s, k), i) for i, s in enumerate(self.words) if seed_length(len(s), share) == k]
            value = np.concatenate([g for g, _ in found])
            item = np.concatenate([np.full(len(g), i) for g, i in found])
            place = np.concatenate([np.arange(len(g)) for g, _ in found])
            order = np.argsort(value, kind="stable")
            self.seeds[k] = value[order], item[order], place[order]
        self.keys = self._keys(self._matrix(self.words), self.sizes, self.sizes) if self.words else None

    @staticmethod
    def _matrix(rows: list[np.ndarray]) -> np.ndarray:
        out = np.zeros((len(rows), max(1, max((len(r) for r in rows), default=1))), np.uint64)
        for k, r in enumerate(rows):
            out[k, : len(r)] = r
        return out

    @staticmethod
    def _keys(windows: np.ndarray, sizes: np.ndarray, item_sizes: np.ndarray) -> np.ndarray:
        """A key for each window and walk; items of equal size share the steps."""
        written = embed(windows, sizes, sampled_steps(item_sizes))
        out = np.zeros(written.shape[:2], np.uint64)
        for k in range(SAMPLES):
            out = mix(out * np.uint64(0x9E3779B97F4A7C15) + written[:, :, k])
        return out

    def search(self, text: np.ndarray) -> list[tuple[int, int, int, int]]:
        """(item_id, start, words, distance) of the closest passage of each item that the text holds."""
        starts, items = [], []
        for k, (value, item, place) in self.seeds.items():
            grams = gram_hashes(text, k)
            low = np.searchsorted(value, grams)
            hit = np.flatnonzero(value[np.minimum(low, len(value) - 1)] == grams)
            if len(hit):
                many = np.searchsorted(value, grams[hit], "right") - low[hit]
                at = np.repeat(low[hit] - np.concatenate(([0], np.cumsum(many)[:-1])), many) + np.arange(many.sum())
                items.append(item[at])
                starts.append(np.maximum(np.repeat(hit, many) - place[at], 0))
        if not items:
            return []
        pairs = np.unique(np.stack((np.concatenate(items), np.concatenate(starts)), axis=1), axis=0)
        best: dict[int, tuple[int, int, int]] = {}
        for at in range(0, len(pairs), 2048):
            item, start = pairs[at : at + 2048].T
            sizes = np.minimum(self.sizes[item], len(text) - start)
            equal = [np.array_equal(text[s : s + n], self.words[i]) for i, s, n in zip(item.tolist(), start.tolist(), sizes.tolist(), strict=True)]
            near = np.array(equal)  # equal windows have equal embeddings, whatever the walk
            other = np.flatnonzero(~near)
            if len(other):
                windows = self._matrix([text[s : s + n] for s, n in zip(start[other].tolist(), sizes[other].tolist(), strict=True)])
                near[other] = (self._keys(windows, sizes[other], self.sizes[item[other]]) == self.keys[item[other]]).any(axis=1)
            for i, s, same in zip(item[near].tolist(), start[near].tolist(), np.array(equal)[near].tolist(), strict=True):
                edits = int(self.edits[i])
                low = max(0, s - edits)
                passage = text[low : s + len(self.words[i]) + edits]
                distance, a, e = (0, s - low, s - low + len(self.words[i])) if same else closest_passage(self.words[i], passage, edits)
                if distance <= edits and (i not in best or (distance, low + a) < best[i][:2]):
                    best[i] = distance, low + a, e - a
        return [(self.ids[i], start, n, distance) for i, (distance, start, n) in sorted(best.items())]


def closest_passage(item: np.ndarray, text: np.ndarray, edits: int) -> tuple[int, int, int]:
    """Least edit distance between the item and any passage of the text, and that passage; the earliest end, then the
    latest start among equals. More than edits: some number above it."""
    if len(text) >= len(item) and edits == 0:
        for a in range(len(text) - len(item) + 1):
            if np.array_equal(text[a : a + len(item)], item):
                return 0, a, a + len(item)
        return 1, 0, 0
    # one number for cost and start: cost * unit - start, so the least is the cheapest, then the one that starts last
    unit, places = len(text) + 1, np.arange(len(text) + 1)
    row, steps = -places, places * unit
    for i, symbol in enumerate(item, 1):
        new = np.empty_like(row)
        new[0] = i * unit
        np.minimum(row[:-1] + np.where(text == symbol, 0, unit), row[1:] + unit, out=new[1:])
        row = np.minimum.accumulate(new - steps) + steps
        if -(-row.min() // unit) > edits:
            return edits + 1, 0, 0
    cost = -(-row // unit)
    end = int(cost.argmin())
    return int(cost[end]), int(cost[end] * unit - row[end]), end


def _search(items: Items):
    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[bytes, list] = {}
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), texts_of(batch.column(1)), strict=True):
                found = known.get(text) if len(text) < 1 << 14 else None
                if found is None:
                    found = items.search(symbols(text))
                    if found and len(text) < 1 << 14:  # copies of a text that holds items are common
                        if len(known) > 1000:
                            known.clear()
                        known[text] = found
                rows += [(doc, *f) for f in found]
            columns = list(zip(*rows, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["doc_id", "item_id", "start", "n_words", "distance"])

    return search


def _holds(items: Items):
    @F.pandas_udf("boolean")
    def holds(text: pd.Series) -> pd.Series:
        return pd.Series([isinstance(t, str) and bool(items.search(symbols(t.encode()))) for t in text], dtype=bool)

    return holds


def item_blocks(benchmark: DataFrame, block_bytes: int = BLOCK_BYTES) -> tuple[int, Callable[[int], tuple[list[int], list[bytes]]]]:
    """How many blocks of about block_bytes the items make, and a function that collects the items of one of them."""
    rows = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("text", F.lit("")).alias("text")).where(F.col("item_id").isNotNull()).distinct()
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, math.ceil(2 * total / block_bytes)) if total > block_bytes else 1

    def block(k: int) -> tuple[list[int], list[bytes]]:
        own = rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k).orderBy("item_id", "text").collect()
        return [r["item_id"] for r in own], [r["text"].encode() for r in own]

    return blocks, block


def contaminated(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, share: float = SHARE, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, item_id, start and n_words (of the passage, in words) and distance for each item that a document holds."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where(F.col("doc_id").isNotNull() & F.col("text").isNotNull())
    blocks, block = item_blocks(benchmark, block_bytes)
    found = None
    for k in range(blocks):
        part = rows.mapInArrow(_search(Items(*block(k), share)), FOUND)
        if blocks > 1:
            part = materialise(part, "contaminated")
        found = part if found is None else found.unionAll(part)
    closest = F.min(F.struct("distance", "start", "n_words")).alias("c")
    return found.groupBy("doc_id", "item_id").agg(closest).select("doc_id", "item_id", "c.start", "c.n_words", "c.distance")


def clean(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, share: float = SHARE, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows of docs that hold no item, unchanged: flagged beside the row, without a join. Rows that hold an item of
    one block aren't searched again for the next."""
    blocks, block = item_blocks(benchmark, block_bytes)
    out = docs
    for k in range(blocks):
        left = out.where(~_holds(Items(*block(k), share))("text"))
        if k < blocks - 1:
            left = materialise(left, "uncontaminated")
            if k:
                forget(out)
        out = left
    return out
