"""Suffix-array dedup over bytes: every byte covered by a `length`-byte string that starts at least twice is removed.

Windows of `length` bytes meet in buckets of their minimiser (see _windows). A bucket builds a suffix array over the
suffixes that start at the minimisers of its distinct strings, by deep-shallow sorting: multikey quicksort over
eight-byte characters down to a shallow depth, then a blind trie for each group that is still tied. The neighbours'
common prefixes of that array, and of the array of the reversed left contexts, tell for each offset of a window which
strings hold it. Strings in which the minimiser occurs more than once are compared by a suffix array of all their
window starts.

Defined results: texts are UTF-8 bytes, a null text is empty; matches never cross documents; overlaps count; windows
are judged on the input. Repeated rows are repeats of each other. Rows with a null doc_id are left out; other columns
are ignored; an empty table gives an empty result. Kept bytes are joined as they are, so they may not be valid UTF-8.
Very long texts are read whole, by segments of SEGMENT windows that overlap by a window.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._windows import SPANS, SPANS_DDL, Entry, Windows, runs_of, without_repeats

SEED_BYTES = 16
SHALLOW = 48
STEP = 8
CELLS = 1 << 17


def common_prefix(a: bytes, b: bytes) -> int:
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    x = int.from_bytes(a[:n], "big") ^ int.from_bytes(b[:n], "big")
    return n - 1 - ((x.bit_length() - 1) >> 3)


def common_suffix(a: bytes, b: bytes) -> int:
    return common_prefix(a[::-1], b[::-1])


def deep_shallow(suffixes: list[bytes], shallow: int = SHALLOW) -> list[int]:
    """Numbers of the suffixes in ascending order, equal ones by number."""
    order: list[int] = []
    stack = [(list(range(len(suffixes))), 0)]
    while stack:
        group, depth = stack.pop()
        if len(group) < 2:
            order += group
        elif depth >= shallow:
            order += _blind(group, suffixes)
        else:
            chars = [suffixes[k][depth : depth + STEP] for k in group]
            pivot = sorted((chars[0], chars[len(chars) // 2], chars[-1]))[1]
            split = [[], [], []]
            for k, c in zip(group, chars, strict=True):
                split[(c >= pivot) + (c > pivot)].append(k)
            ended = len(pivot) < STEP  # then the tied ones end here and are equal
            stack += [(split[2], depth), (split[1], shallow if ended else depth + STEP), (split[0], depth)]
    return order


class _Node:
    """A branch of a blind trie: the depth at which its suffixes first differ, and a child for each byte there."""

    __slots__ = ("children", "depth")

    def __init__(self, depth: int) -> None:
        self.depth, self.children = depth, {}


def _blind(group: list[int], suffixes: list[bytes]) -> list[int]:
    """Order of a group with a long common prefix. A leaf is a list of equal suffixes; a branch looks at one byte."""
    root: _Node | list[int] = [group[0]]
    for k in group[1:]:
        new, node, path = suffixes[k], root, []
        while isinstance(node, _Node):
            path.append(node)
            at = new[node.depth] if node.depth < len(new) else -1
            node = node.children.get(at) or next(iter(node.children.values()))
        old = suffixes[node[0]]
        same = common_prefix(new, old)
        if same == len(new) == len(old):
            node.append(k)
            continue
        inner = next((p for p in path if p.depth >= same), None)
        at = new[same] if same < len(new) else -1
        if inner is not None and inner.depth == same:
            inner.children[at] = [k]
            continue
        branch = _Node(same)
        branch.children[at] = [k]
        branch.children[old[same] if same < len(old) else -1] = inner if inner is not None else node
        above = path[path.index(inner) - 1] if inner is not None and path.index(inner) else path[-1] if inner is None and path else None
        if above is None:
            root = branch
        else:
            above.children[new[above.depth] if above.depth < len(new) else -1] = branch
    order: list[int] = []
    stack = [root]
    while stack:
        node = stack.pop()
        if isinstance(node, _Node):
            stack += [node.children[c] for c in sorted(node.children, reverse=True)]
        else:
            order += sorted(node)
    return order


def _neighbours(order: list[int], texts: list[bytes]) -> np.ndarray:
    """Common prefix of each text with the one before it in the order."""
    return np.array([common_prefix(texts[a], texts[b]) for a, b in zip(order, order[1:])], np.int32)


def _classes(order: np.ndarray, near: np.ndarray, depths: np.ndarray) -> np.ndarray:
    """depths x texts: texts with one number in a row agree in their first `depth` bytes and have that many."""
    numbers = np.zeros((len(depths), len(order)), np.int64)
    numbers[:, order[1:]] = np.cumsum(near[None, :] < depths[:, None], axis=1, dtype=np.int64)
    return numbers


def _anchored(group: list[Entry], order: list[int], length: int, seed: int) -> list[np.ndarray]:
    """Which windows of each entry are unique; order: of the suffixes at the anchors."""
    lone = [np.full(e.n, e.count < 2) for e in group]
    rights = [e.text[e.anchor :] for e in group]
    if len(group) <= 3:
        for i, a in enumerate(group):
            for j in range(i):
                b = group[j]
                right, left = common_prefix(rights[i], rights[j]), common_suffix(a.text[: a.anchor], b.text[: b.anchor])
                for flags, e in ((lone[i], a), (lone[j], b)):
                    low, high = e.anchor - left, e.anchor - (length - right)
                    if high >= max(low, 0):
                        flags[max(low, 0) : high + 1] = False
        return lone
    lefts = [e.text[: e.anchor][::-1] for e in group]
    left_order = deep_shallow(lefts)
    near_right, near_left = _neighbours(order, rights), _neighbours(left_order, lefts)
    del rights, lefts
    right_order, left_order = np.array(order), np.array(left_order)
    anchors, sizes = np.array([e.anchor for e in group]), np.array([e.n for e in group])
    begins, flat = np.cumsum(sizes) - sizes, np.concatenate(lone)
    step = max(1, CELLS // len(group))
    for low in range(0, length - seed + 1, step):  # some offsets at a time: memory follows the group, not 185 times it
        offsets = np.arange(low, min(low + step, length - seed + 1))
        both = _classes(left_order, near_left, offsets) * len(group) + _classes(right_order, near_right, length - offsets)
        ranked = np.argsort(both, axis=1)
        both = np.take_along_axis(both, ranked, axis=1)
        same = both[:, 1:] == both[:, :-1]
        twice = np.zeros(both.shape, bool)
        twice[:, 1:] |= same
        twice[:, :-1] |= same
        row, at = np.nonzero(twice)
        entry = ranked[row, at]
        window = anchors[entry] - offsets[row]
        valid = (window >= 0) & (window < sizes[entry])
        flat[begins[entry[valid]] + window[valid]] = False
    return np.split(flat, begins[1:])


def _all_starts(group: list[Entry], length: int) -> list[np.ndarray]:
    lone = [np.full(e.n, e.count < 2) for e in group]
    places = [(k, i) for k, e in enumerate(group) for i in range(e.n)]
    windows = [group[k].text[i : i + length] for k, i in places]
    order = deep_shallow(windows)
    for a, b in zip(order, order[1:]):
        if windows[a] == windows[b]:
            for k, i in (places[a], places[b]):
                lone[k][i] = False
    return lone


def _judge(length: int, seed: int):
    def judge(groups: list[list[Entry]]) -> list[list[np.ndarray]]:
        anchored = [g if all(e.anchor >= 0 for e in g) else None for g in groups]
        members = [(k, i) for k, g in enumerate(anchored) for i in range(len(g or ())) if len(g) > 3]
        orders: dict[int, list[int]] = {}
        for at in deep_shallow([anchored[k][i].text[anchored[k][i].anchor :] for k, i in members]):
            k, i = members[at]
            orders.setdefault(k, []).append(i)
        return [_all_starts(g, length) if a is None else _anchored(g, orders.get(k, []), length, seed) for k, (g, a) in enumerate(zip(groups, anchored, strict=True))]

    return judge


def _strike(text: bytes, removed: Callable) -> tuple:
    starts, ends = runs_of(removed(len(text)))
    kept = b"".join(text[a:b] for a, b in zip([0, *ends], [*starts, len(text)], strict=True)) if starts else text
    return len(text), [{"start": a, "end": b} for a, b in zip(starts, ends, strict=True)], kept


def repeated_bytes(docs: DataFrame, length: int = 200) -> DataFrame:
    """doc_id, n_bytes, removed (maximal spans of bytes, end exclusive) and kept (the other bytes)."""
    seed = max(8, min(SEED_BYTES, length // 8 * 8))
    windows = Windows(length, seed, words=False)
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("removed", SPANS), ("kept", pa.binary())])
    return without_repeats(docs, windows, _judge(length, seed), 1, _strike, schema, f"doc_id long, n_bytes long, removed {SPANS_DDL}, kept binary")


def digest(found: DataFrame) -> DataFrame:
    removed = F.aggregate("removed", F.lit(0).cast("long"), lambda total, s: total + s["end"] - s["start"])
    return found.select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("removed").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))
