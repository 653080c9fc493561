"""Pairs drawn one by one: every pair of ids is hashed in the task of two blocks of ids, and only drawn pairs leave it."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..rng import pairs_under
from .state import write_state

SIDE = 4096
RANGE = 1 << 16
CELLS = 4096


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Ids in order and their kinds, as blocks of SIDE."""
    held = [tuple(c.to_numpy() for c in batch.columns) for batch in batches if batch.num_rows]
    if held:
        ids, kinds = (np.concatenate(c) for c in zip(*held))
        for at in range(0, len(ids), SIDE):
            own = ids[at : at + SIDE]
            yield pa.RecordBatch.from_arrays([pa.array([x]) for x in (int(own[0]), int(own[-1]), own.tobytes(), kinds[at : at + SIDE].tobytes())], ["low", "high", "ids", "kinds"])


def pairs_drawn(ids: DataFrame, key: str, kind: Column, chances: np.ndarray, seed: int, purpose: str) -> DataFrame:
    """src, dst: the pairs src < dst of a column of ids whose portable(seed, purpose, src, dst) is under
    chances[kind of src, kind of dst]; kind: from 0. Repeated ids count as often as they are there, nulls never."""
    most = float(chances.max(initial=0.0))

    def draw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                left, right = (np.frombuffer(row[c], np.int64) for c in ("ids", "others"))
                one, other = (np.frombuffer(row[c], np.int32) for c in ("kinds", "kinds2"))
                for i, j, u in pairs_under(seed, purpose, left, right, most):
                    kept = u < chances[one[i], other[j]]
                    yield pa.RecordBatch.from_arrays([pa.array(left[i[kept]]), pa.array(right[j[kept]])], ["src", "dst"])

    rows = ids.where(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), kind.cast("int").alias("kind"))
    n = rows.count()
    ordered = rows.repartitionByRange(max(1, math.ceil(n / RANGE)), "id").sortWithinPartitions("id")
    blocks = write_state(ordered.mapInArrow(_blocks, "low long, high long, ids binary, kinds binary").withColumn("no", F.monotonically_increasing_id()), "blocks")
    place = F.struct("low", "high", "no")  # blocks are disjoint ranges but for their ends, so all of the first are at or below the second
    many = blocks.count()
    first, second = blocks.select(place.alias("x"), "ids", "kinds"), blocks.select(place.alias("y"), F.col("ids").alias("others"), F.col("kinds").alias("kinds2"))
    cells = first.crossJoin(second.hint("shuffle_replicate_nl")).where("x <= y").drop("x", "y")
    type_of = ids.schema[key].dataType
    return cells.repartition(max(1, min(CELLS, many * (many + 1) // 2))).mapInArrow(draw, "src long, dst long").select(*[F.col(c).cast(type_of).alias(c) for c in ("src", "dst")])
