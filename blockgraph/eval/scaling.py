"""Seconds against the number of tasks, and bytes of state."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame

from ..plans.state import drop_state, write_state


def scaling(edges: DataFrame, run: Callable[[DataFrame], object], tasks: tuple[int, ...] = (1, 2, 4)) -> DataFrame:
    """tasks, seconds: the same run with edges dealt to that many partitions and as many shuffle partitions."""
    spark, rows = edges.sparkSession, []
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for n in tasks:
            spark.conf.set("spark.sql.shuffle.partitions", n)
            dealt = write_state(edges.repartition(n), "dealt")
            began = time.monotonic()
            run(dealt)
            rows.append((n, time.monotonic() - began))
            drop_state(dealt)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    return spark.createDataFrame(rows, "tasks int, seconds double")


def state_bytes(state: DataFrame) -> int:
    """Bytes of a state as it is written between rounds."""
    written = write_state(state, "sized")
    jvm = state.sparkSession._jvm
    place = jvm.org.apache.hadoop.fs.Path(written._state_path)
    size = place.getFileSystem(state.sparkSession._jsparkSession.sessionState().newHadoopConf()).getContentSummary(place).getLength()
    drop_state(written)
    return size
