"""Helpers that the operators of this folder share: tables, scratch storage and byte-level numpy."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

ODD = np.uint64(0x9E3779B97F4A7C15)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def scratch_folder(spark: SparkSession) -> str:
    """The shared folder for tables that cut lineage: the session's own, else one for a single machine."""
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir") or context._jsc.sc().getCheckpointDir().getOrElse(None)
    if not folder:
        folder = tempfile.mkdtemp(prefix="blockgraph-")
        context.setCheckpointDir(folder)
        folder = context._jsc.sc().getCheckpointDir().get()
    return folder.rstrip("/")


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write df to the shared folder and read it back: a lost executor re-reads it instead of recomputing."""
    spark = df.sparkSession
    path = f"{scratch_folder(spark)}/tables/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return _with_path(spark.read.schema(df.schema).parquet(path), path)


def _with_path(df: DataFrame, path: str) -> DataFrame:
    df._scratch_path = path
    return df


def forget(df: DataFrame) -> None:
    """Delete what materialise() wrote for df; later reads of it fail."""
    jvm, path = df.sparkSession._jvm, df._scratch_path
    place = jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(place, True)


def text_key(text: Column) -> Column:
    """Tells rows apart that carry one doc_id and different texts."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (fixed values: the two multipliers and three shifts of splitmix64)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each run of width neighbours, by doubling."""
    reach, out = 1, values
    while reach < width:
        step = min(reach, width - reach)
        out = np.minimum(out[:-step], out[step:])
        reach += step
    return out


def texts_of(column: pa.Array) -> Iterator[bytes]:
    """UTF-8 bytes of each row, null as empty; few rows at a time become Python objects."""
    column = column.cast(pa.binary())
    for at in range(0, len(column), 128):
        for value in column.slice(at, 128).to_pylist():
            yield value or b""


WORD_BREAKS = np.zeros(256, bool)
WORD_BREAKS[[0x20, *range(0x09, 0x0E)]] = True


def word_bounds(data: np.ndarray, breaks: np.ndarray = WORD_BREAKS) -> tuple[np.ndarray, np.ndarray]:
    """Start and end byte of each maximal run of bytes that are no breaks."""
    inside = np.zeros(len(data) + 2, np.int8)
    inside[1:-1] = ~breaks[data]
    edge = np.diff(inside)
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


_POWERS = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS[0]) < n:
        size = max(n, 2 * len(_POWERS[0]), 4096)
        inverse = np.uint64(pow(int(ODD), -1, 1 << 64))
        for k, base in ((0, ODD), (1, inverse)):
            factors = np.full(size, base, np.uint64)
            factors[0] = 1
            _POWERS[k] = np.cumprod(factors, dtype=np.uint64)
    return _POWERS[0], _POWERS[1]


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the bytes of each word, from one prefix sum; equal words get equal hashes."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    block = 1 << 20
    if len(data) > block:  # long texts by blocks of words: the power tables stay small
        out, k = [], 0
        while k < len(starts):
            m = max(k + 1, int(np.searchsorted(ends, starts[k] + block, "right")))
            a, b = int(starts[k]), int(ends[m - 1])
            out.append(_hash_block(data[a:b], starts[k:m] - a, ends[k:m] - a))
            k = m
        return np.concatenate(out)
    return _hash_block(data, starts, ends)


def _hash_block(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    up, down = _powers(len(data) + 1)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=sums[1:])
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def gram_hashes(units: np.ndarray, k: int) -> np.ndarray:
    """A 64-bit hash of each k consecutive units."""
    n = len(units) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j in range(k):
        out = out * ODD + units[j : j + n]
    return mix(out)
