"""Substring dedup over words: super-k-mer partitioning.

Words are maximal runs of bytes other than space and the five ASCII controls 0x09-0x0D, taken unchanged. Every window
of `length` words that also starts earlier (smaller doc_id, or same document and earlier start) is a repeat, judged on
the input; the words it covers are removed. Consecutive windows with one minimiser travel as one packed string to its
bucket (see _windows), where sorting the windows of a minimiser brings equal ones together and keeps the earliest.

Defined results: a null text has no words; texts shorter than a window lose nothing; a row that repeats another's
doc_id and text is the same document twice and gets the same answer; rows with one doc_id and different texts are
documents of their own, ordered by a hash of the text; rows with a null doc_id are left out; other columns are ignored;
an empty table gives an empty result. Texts of any length are read whole: one text, its hashes and its answer are in a
task's memory at a time, never a prefix.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Callable
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._windows import SPANS, SPANS_DDL, Entry, Windows, runs_of, without_repeats

SEED_WORDS = 4


def _breaks(text: bytes) -> list[int]:
    return [-1, *(i for i, c in enumerate(text) if c == 0x20), len(text)]


def _keep_earliest(windows: list[tuple], stays: list[np.ndarray]) -> None:
    """Sorting brings equal windows together, the earliest first; it stays. windows: (words, place, entry, number)."""
    windows.sort()
    for _, same in groupby(windows, key=lambda w: w[0]):
        *_, k, i = next(same)
        stays[k][i] = True


def _judge(length: int):
    def judge(groups: list[list[Entry]]) -> list[list[np.ndarray]]:
        answers = []
        for group in groups:
            stays = [np.zeros(e.n, bool) for e in group]
            breaks = [_breaks(e.text) for e in group]

            def window(k: int, i: int) -> tuple:
                e, at = group[k], breaks[k]
                doc, key, first = e.place
                return e.text[at[i] + 1 : at[i + length]], doc, key, first + i, k, i

            if any(e.anchor < 0 for e in group):
                _keep_earliest([window(k, i) for k, e in enumerate(group) for i in range(e.n)], stays)
            else:  # equal windows have the minimiser at the same offset: one offset at a time
                anchors = [bisect_left(at, e.anchor) - 1 for at, e in zip(breaks, group, strict=True)]
                for offset in range(max(anchors) + 1):
                    _keep_earliest([window(k, a - offset) for k, a in enumerate(anchors) if 0 <= a - offset < group[k].n], stays)
            answers.append(stays)
        return answers

    return judge


def _strike(text: bytes, removed: Callable) -> tuple:
    words = text.split()
    starts, ends = runs_of(removed(len(words)))
    at, parts = 0, []
    for a, b in zip(starts, ends, strict=True):
        parts += words[at:a]
        at = b
    return len(words), [{"start": a, "end": b} for a, b in zip(starts, ends, strict=True)], b" ".join(parts + words[at:] if at else words).decode()


def repeated_words(docs: DataFrame, length: int = 20) -> DataFrame:
    """doc_id, n_words, removed (spans of word numbers, end exclusive) and kept_text (kept words joined by a space)."""
    windows = Windows(length, min(SEED_WORDS, length), words=True)
    schema = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("removed", SPANS), ("kept_text", pa.string())])
    return without_repeats(docs, windows, _judge(length), 1 << 62, _strike, schema, f"doc_id long, n_words long, removed {SPANS_DDL}, kept_text string")


def digest(found: DataFrame) -> DataFrame:
    removed = F.aggregate("removed", F.lit(0).cast("long"), lambda total, s: total + s["end"] - s["start"])
    return found.select("doc_id", "n_words", removed.alias("n_removed"), F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))
