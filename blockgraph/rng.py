"""Randomness as a pure function of keys: the same draw on every retry, partitioning and engine."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

HEX_DIGITS = 13
SPAN = float(1 << (4 * HEX_DIGITS))


def _text(seed: int, purpose: str, keys: tuple) -> Column:
    return F.concat_ws("|", F.lit(str(seed)), F.lit(purpose), *[(k if isinstance(k, Column) else F.lit(k)).cast("string") for k in keys])


def uniform_of(text: Column) -> Column:
    """A number in [0, 1) from the md5 of a text; DuckDB computes the same one."""
    return F.conv(F.substring(F.md5(text), 1, HEX_DIGITS), 16, 10).cast("long") / F.lit(SPAN)


def portable(seed: int, purpose: str, *keys: Column | int | str) -> Column:
    return uniform_of(_text(seed, purpose, keys))


# Fixed values of MD5: the rotations of its four turns and the starting state. Its 64 addends follow from a rule.
ROTATIONS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
STARTING_STATE = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
ADDENDS = np.floor(np.abs(np.sin(np.arange(1, 65))) * 2.0**32).astype(np.uint32)
ONE_BLOCK = 55
DECIMALS = 20
AT_ONCE = 1 << 12
PAIRS_AT_ONCE = 1 << 16


def decimals(ids: np.ndarray) -> np.ndarray:
    """Ids in decimals: one row of bytes each, zeros behind."""
    texts = np.ascontiguousarray(np.asarray(ids, np.int64).astype(f"S{DECIMALS}"))
    return texts.view(np.uint8).reshape(len(texts), DECIMALS)


def _md5_heads(prefix: bytes, digits: np.ndarray) -> np.ndarray:
    """First 8 bytes of the md5 of prefix and each row of digits, as big-endian numbers; texts of one block only."""
    length = len(prefix) + (digits != 0).sum(axis=1)
    block = np.zeros((len(digits), 64), np.uint8)
    block[:, : len(prefix)] = np.frombuffer(prefix, np.uint8)
    block[:, len(prefix) : len(prefix) + DECIMALS] = digits
    block[np.arange(len(digits)), length] = 0x80
    words = np.ascontiguousarray(block.view("<u4").T)
    words[14] = 8 * length
    a, b, c, d = (np.full(len(digits), x, np.uint32) for x in STARTING_STATE)
    for turn, rotations in enumerate(ROTATIONS):
        for k in range(16):
            if turn == 0:
                mixed, word = d ^ (b & (c ^ d)), k
            elif turn == 1:
                mixed, word = c ^ (d & (b ^ c)), 5 * k + 1
            elif turn == 2:
                mixed, word = b ^ c ^ d, 3 * k + 5
            else:
                mixed, word = c ^ (b | ~d), 7 * k
            mixed += a
            mixed += words[word % 16]
            mixed += ADDENDS[16 * turn + k]
            by = rotations[k % 4]
            a, b, c, d = d, b + (mixed << np.uint32(by) | mixed >> np.uint32(32 - by)), b, c
    high, low = ((x + np.uint32(first)).byteswap().astype(np.uint64) for x, first in zip((a, b), STARTING_STATE))
    return high << np.uint64(32) | low


def portable_numpy(seed: int, purpose: str, round_: int, ids: np.ndarray) -> np.ndarray:
    """portable(seed, purpose, round_, id) for an array of ids, or for decimals(ids), outside Spark."""
    prefix, digits = f"{seed}|{purpose}|{round_}|".encode(), ids if ids.ndim == 2 else decimals(ids)
    if len(prefix) + DECIMALS > ONE_BLOCK:
        return portable_texts(seed, purpose, [f"{round_}|{bytes(row[row != 0]).decode()}" for row in digits])
    heads = [_md5_heads(prefix, digits[at : at + AT_ONCE]) for at in range(0, len(digits), AT_ONCE)]
    return (np.concatenate([np.zeros(0, np.uint64), *heads]) >> np.uint64(64 - 4 * HEX_DIGITS)) / SPAN


def _runs_of(texts: np.ndarray) -> list[slice]:
    """Rows of digits by runs of equal length."""
    lengths = (texts != 0).sum(axis=1)
    ends = np.flatnonzero(np.diff(lengths)) + 1
    return [slice(a, b) for a, b in zip([0, *ends], [*ends, len(texts)]) if b > a]


def _pair_heads(first: np.ndarray, second: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the md5 of each pair, as big-endian numbers: its message is the sum of a row of `first` and
    one of `second` (16 words each). A word that only one side has is never spread over the pairs."""
    shape, words = (len(first), len(second)), []
    for w in range(16):
        x, y = first[:, w, None], second[None, :, w]
        words.append(x + y if x.any() and y.any() else y if y.any() else x)
    a, b, c, d = (np.full(shape, x, np.uint32) for x in STARTING_STATE)
    mixed, kept = np.empty(shape, np.uint32), np.empty(shape, np.uint32)
    for turn, rotations in enumerate(ROTATIONS):
        for k in range(16):
            if turn == 0:
                word = k
                np.bitwise_xor(c, d, out=mixed)
                mixed &= b
                mixed ^= d
            elif turn == 1:
                word = 5 * k + 1
                np.bitwise_xor(b, c, out=mixed)
                mixed &= d
                mixed ^= c
            elif turn == 2:
                word = 3 * k + 5
                np.bitwise_xor(b, c, out=mixed)
                mixed ^= d
            else:
                word = 7 * k
                np.invert(d, out=mixed)
                mixed |= b
                mixed ^= c
            x, addend = words[word % 16], ADDENDS[16 * turn + k]
            mixed += a
            if x.shape == shape:
                mixed += x
                mixed += addend
            else:
                mixed += x + addend
            by = rotations[k % 4]
            np.left_shift(mixed, np.uint32(by), out=kept)
            mixed >>= np.uint32(32 - by)
            mixed |= kept
            mixed += b
            a, b, c, d, mixed = d, mixed, b, c, a
    a += np.uint32(STARTING_STATE[0])
    b += np.uint32(STARTING_STATE[1])
    return a.byteswap(inplace=True), b.byteswap(inplace=True)


def pairs_under(seed: int, purpose: str, left: np.ndarray, right: np.ndarray, most: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Positions x, y of the pairs with left[x] < right[y], and portable(seed, purpose, left[x], right[y]) of each pair for which it is
    under `most`; all pairs are hashed, some at a time. left and right are in order."""
    prefix = f"{seed}|{purpose}|".encode()
    if len(prefix) + 2 * DECIMALS + 1 > ONE_BLOCK:
        raise ValueError(f"{purpose} is too long for one block of md5")
    texts, limit = [decimals(left), decimals(right)], min(int(max(most, 0.0) * 2.0**32), (1 << 32) - 1)
    for own in _runs_of(texts[0]):
        digits = texts[0][own]
        at = len(prefix) + int((digits[0] != 0).sum())
        first = np.zeros((len(digits), 64), np.uint8)
        first[:, : len(prefix)] = np.frombuffer(prefix, np.uint8)
        first[:, len(prefix) : at] = digits[:, : at - len(prefix)]
        first[:, at] = ord("|")
        for other in _runs_of(texts[1]):
            digits = texts[1][other]
            end = at + 1 + int((digits[0] != 0).sum())
            second = np.zeros((len(digits), 64), np.uint8)
            second[:, at + 1 : end] = digits[:, : end - at - 1]
            second[:, end] = 0x80
            second[:, 56:58] = np.frombuffer((8 * end).to_bytes(2, "little"), np.uint8)
            x, lines = own.start, [np.ascontiguousarray(m).view("<u4") for m in (first, second)]
            while x < own.stop:
                y = max(other.start, int(np.searchsorted(right, left[x], "right")))
                if y >= other.stop:
                    break  # ids to the left only grow
                many = max(1, PAIRS_AT_ONCE // (other.stop - y))
                high, low = _pair_heads(lines[0][x - own.start : x - own.start + many], lines[1][y - other.start :])
                found = np.flatnonzero(high.ravel() <= limit)
                u = (high.ravel()[found].astype(np.uint64) << np.uint64(32) | low.ravel()[found]) >> np.uint64(64 - 4 * HEX_DIGITS)
                i, j, u = x + found // high.shape[1], y + found % high.shape[1], u / SPAN
                kept = (left[i] < right[j]) & (u < most)
                yield i[kept], j[kept], u[kept]
                x += many


def portable_texts(seed: int, purpose: str, keys: list[str]) -> np.ndarray:
    """portable(seed, purpose, ...) for texts of the remaining keys, joined by |, outside Spark."""
    prefix = f"{seed}|{purpose}|"
    digests = b"".join(hashlib.md5(f"{prefix}{k}".encode()).digest() for k in keys)
    return (np.frombuffer(digests, ">u8")[::2] >> np.uint64(64 - 4 * HEX_DIGITS)) / SPAN


def fast(seed: int, purpose: str, *keys: Column | int | str) -> Column:
    """The same idea over xxhash64: not portable, cheaper."""
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(purpose), *[k if isinstance(k, Column) else F.lit(k) for k in keys]), 11) / F.lit(float(1 << 53))


def uniform_sql(text: str) -> str:
    return f"(('0x' || substr(md5({text}), 1, {HEX_DIGITS}))::BIGINT / {SPAN:.1f})"


def portable_sql(seed: int, purpose: str, *keys: str) -> str:
    """DuckDB's twin of portable(); keys are SQL expressions."""
    return uniform_sql("concat_ws('|', " + ", ".join([f"'{seed}'", f"'{purpose}'", *[f"CAST({k} AS VARCHAR)" for k in keys]]) + ")")


def cumulative(vec: Column) -> Column:
    """Running sums of a vector, in one pass."""

    @F.pandas_udf("array<double>")
    def running(vectors: pd.Series) -> pd.Series:
        return vectors.map(np.cumsum)

    return running(vec)


def search_steps(blocks: int) -> list[int]:
    """Falling powers of two for a binary search among `blocks` running sums."""
    return [1 << k for k in reversed(range(max(1, blocks.bit_length())))]


def draw_block(cum: Column, u: Column, blocks: int = 1 << 16) -> Column:
    """Which block a uniform number falls into: the first running sum above it, the last block past the end. By binary
    search: log2(blocks) looks, where cum has at most `blocks` sums."""
    jump = lambda at, step: F.when(F.get(cum, at + step - 1) <= u, at + step).otherwise(at)  # null past the end: stay
    below = F.aggregate(F.array(*[F.lit(k) for k in search_steps(blocks)]), F.lit(0), jump)
    return F.least(below, F.size(cum) - 1).cast("int")


def draw_rows(cum: np.ndarray, u: np.ndarray) -> np.ndarray:
    """draw_block for rows of running sums (rows x blocks) and uniform numbers (rows x draws)."""
    rows, blocks = cum.shape
    flat, first = cum.ravel(), np.arange(rows)[:, None] * blocks
    at = np.zeros(u.shape, np.int64)
    for step in search_steps(blocks):
        ahead = at + step
        at = np.where((ahead <= blocks) & (flat[first + np.minimum(ahead, blocks) - 1] <= u), ahead, at)
    return np.minimum(at, blocks - 1)


def alias_arrays(vec: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Probability and alias of each slot of an alias table: one draw then costs O(1)."""
    n = len(vec)
    share = np.asarray(vec, float) * n / np.sum(vec)
    keep, other = np.ones(n), np.arange(n)
    small, large = [i for i in range(n) if share[i] < 1], [i for i in range(n) if share[i] >= 1]
    while small and large:
        s, g = small.pop(), large[-1]
        keep[s], other[s] = share[s], g
        share[g] -= 1 - share[s]
        if share[g] < 1:
            small.append(large.pop())
    return keep, other


def alias_table(vec: Column) -> Column:
    """struct(keep, other) for a column of vectors."""

    @F.pandas_udf("struct<keep:array<double>,other:array<int>>")
    def build(vectors: pd.Series) -> pd.DataFrame:
        pairs = [alias_arrays(np.asarray(v)) for v in vectors]
        return pd.DataFrame({"keep": [k for k, _ in pairs], "other": [o.astype(np.int32) for _, o in pairs]})

    return build(vec)


def draw_alias(table: Column, u: Column) -> Column:
    """A block from an alias table by one uniform number."""
    slot = F.floor(u * F.size(table["keep"])).cast("int")
    rest = u * F.size(table["keep"]) - slot
    return F.when(rest < F.get(table["keep"], slot), slot).otherwise(F.get(table["other"], slot))


def numpy_uniform_pair(seed: int, *keys: np.ndarray | int) -> tuple[np.ndarray, np.ndarray]:
    """Two uniform numbers of 32 bits each from one hash of integer keys."""
    state = _mixed(seed, keys)
    return (state >> np.uint64(32)) / float(1 << 32), (state & np.uint64(0xFFFFFFFF)) / float(1 << 32)


def numpy_uniform(seed: int, *keys: np.ndarray | int) -> np.ndarray:
    """Uniform numbers from integer keys, for the Arrow backends."""
    return (_mixed(seed, keys) >> np.uint64(11)) / float(1 << 53)


def _mixed(seed: int, keys: tuple) -> np.ndarray:
    state = np.uint64((seed & 0xFFFFFFFF) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    with np.errstate(over="ignore"):
        for key in keys:
            state = (np.asarray(key).astype(np.uint64) + state) * np.uint64(0xBF58476D1CE4E5B9)
            state = (state ^ (state >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
            state = state ^ (state >> np.uint64(32))
    return state
