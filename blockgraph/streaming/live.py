"""Streams around a fit: windows of edges, hits under frozen labels, fold-in of users, scoring, per-user state."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from ..hard.stats import labelled
from ..soft import predict, steps
from ..soft.model import attach, neighbour_mean

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str) -> DataFrame:
    """Parquet files of events as they arrive; ts becomes an instant, which watermarks need."""
    return spark.readStream.schema(EVENTS).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def rating_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Deduplicated (src, dst, ts) edges of users and keys within the watermark."""
    edges = events.withColumn("dst", F.from_json("props", "k int")["k"].cast("long")).withColumnRenamed("user_id", "src").where("dst IS NOT NULL")
    return edges.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]).select("src", "dst", "ts", "event_type")


def edge_windows(edges: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return edges.groupBy(window.alias("w"), "src", "dst").agg(F.count("*").alias("n")).select("w.start", "w.end", "src", "dst", "n")


def sessions(edges: DataFrame, gap: str = "1 hour") -> DataFrame:
    return edges.groupBy(F.session_window("ts", gap).alias("w"), "src").agg(F.count("*").alias("n")).select("w.start", "w.end", "src", "n")


def live_hits(edges: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """a, b, hit: block-pair hits under frozen labels, for update mode."""
    return labelled(edges, left, right).groupBy("a", "b").agg(F.count("*").alias("hit"))


def fold_in(edges: DataFrame, right: DataFrame, cat: DataFrame, sizes: tuple[int, int, int], rounds: int = 1) -> DataFrame:
    """id, vec for users from their edges alone: rounds of the exact update with items and tensor frozen."""
    na, nb, nc = sizes
    mem = edges.select(F.col("src").alias("id")).distinct().withColumn("vec", F.array(*[F.lit(1.0 / na)] * na))
    for _ in range(rounds):
        shared = steps._shared(attach(edges, mem, right, cat), na, nb, nc)
        mem = neighbour_mean(shared.select(F.col("src").alias("id"), F.col("sl").alias("share")), na)
    return mem


def fold_in_batches(right: DataFrame, cat: DataFrame, sizes: tuple[int, int, int], sink: str) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: memberships of a batch's users, appended under its number so that a replay overwrites."""

    def batch(edges: DataFrame, number: int) -> None:
        fold_in(edges, right, cat, sizes).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return batch


def live_scores(pairs: DataFrame, left: DataFrame, right: DataFrame, cat: DataFrame, values: DataFrame) -> DataFrame:
    """Expected ratings of a stream of pairs."""
    return predict.soft(pairs, left, right, cat, values)


def clicks_to_purchases(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Purchases within an interval after a click of the same user, by a watermarked join."""
    a = clicks.select(F.col("user_id").alias("src"), F.col("event_id").alias("click_id"), F.col("ts").alias("click_ts")).withWatermark("click_ts", late)
    b = purchases.select(F.col("user_id").alias("buyer"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("purchase_ts")).withWatermark("purchase_ts", late)
    near = (F.col("src") == F.col("buyer")) & (F.col("purchase_ts") >= F.col("click_ts")) & (F.col("purchase_ts") <= F.col("click_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, near).select("src", "click_id", "purchase_id", "click_ts", "purchase_ts")


def read_rate(spark: SparkSession, rows_per_second: int = 100, vertices: int = 1000) -> DataFrame:
    """src, dst, ts: a synthetic stream of edges, for load tests."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    end = lambda k: F.pmod(F.xxhash64("value", F.lit(k)), F.lit(vertices))
    return rows.select(end(0).alias("src"), end(1).alias("dst"), F.col("timestamp").alias("ts"))


def late_rows(query: StreamingQuery) -> int:
    """Rows that came behind the watermark and were dropped, over the progress that the query still remembers."""
    return sum(operator["numRowsDroppedByWatermark"] for progress in query.recentProgress for operator in progress["stateOperators"])


USER_COUNTS = "user_id long, n long, closed boolean"


class IdleCounts(StatefulProcessor):
    """Counts rows of a key; a timer in event time closes and forgets it when it stays idle for `idle_ms`."""

    def __init__(self, idle_ms: int) -> None:
        self.idle_ms = idle_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.count = handle.getValueState("count", "n long, due long")

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timerValues: object) -> Iterator[pd.DataFrame]:  # noqa: N802, N803  names of the interface
        n, due = self.count.get() if self.count.exists() else (0, 0)
        latest = 0
        for frame in rows:
            n += len(frame)
            latest = max(latest, int(frame["ts"].max().timestamp() * 1000))
        later = max(due, latest + self.idle_ms, timerValues.getCurrentWatermarkInMs() + 1)
        if due and later != due:
            self.handle.deleteTimer(due)
        if later != due:
            self.handle.registerTimer(later)
        self.count.update((n, later))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "closed": [False]})

    def handleExpiredTimer(self, key: tuple, timerValues: object, expiredTimerInfo: object) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        n, _ = self.count.get()
        self.count.clear()
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "closed": [True]})

    def close(self) -> None:
        pass


def user_counts(events: DataFrame, idle: str = "2 hours") -> DataFrame:
    """user_id, n, closed: running event counts of each user, closed when it stays idle for that long in event time.

    Keyed state with timers; the session's state store must be the RocksDB one, which Spark asks for here.
    """
    rows = events.withWatermark("ts", "1 hour").select("user_id", "ts")
    processor = IdleCounts(int(pd.Timedelta(idle).total_seconds() * 1000))
    return rows.groupBy("user_id").transformWithStateInPandas(processor, outputStructType=USER_COUNTS, outputMode="Update", timeMode="EventTime")
