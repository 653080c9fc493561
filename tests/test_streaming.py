import pytest
from pyspark.sql import functions as F

from blockgraph.soft import steps
from blockgraph.sources import tables as t
from blockgraph.streaming import live


@pytest.fixture
def events(spark, sf, tmp_path):
    source = tmp_path / "in"
    spark.read.parquet(f"{sf}/events.parquet").repartition(3).write.parquet(str(source))
    return live.read_events(spark, str(source))


def drained(df, name, tmp_path, mode="append"):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", str(tmp_path / f"ck-{name}")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return df.sparkSession.table(name)


def test_daily_edges_equal_the_batch(spark, sf, events, tmp_path):
    out = drained(live.edge_windows(live.rating_events(events, "60 days")), "daily", tmp_path, "update")
    batch = spark.read.parquet(f"{sf}/events.parquet").withColumn("dst", F.from_json("props", "k int")["k"].cast("long")).groupBy(F.window("ts", "1 day"), "user_id", "dst").agg(F.count("*").alias("n"))
    best = out.groupBy("start", "src", "dst").agg(F.max("n").alias("n"))
    assert best.count() == batch.count() and best.agg(F.sum("n")).first()[0] == batch.agg(F.sum("n")).first()[0]


def test_live_hits_and_scores(spark, sf, events, tmp_path):
    edges = live.rating_events(events, "60 days")
    ids = spark.read.parquet(f"{sf}/events.parquet").select(F.col("user_id").alias("id")).distinct()
    left = ids.select("id", (F.col("id") % 2).cast("int").alias("lab"))
    right = spark.range(100).select("id", (F.col("id") % 3).cast("int").alias("lab"))
    hits = drained(live.live_hits(edges, left, right), "hits", tmp_path, "update").groupBy("a", "b").agg(F.max("hit").alias("hit"))
    assert hits.agg(F.sum("hit")).first()[0] == spark.read.parquet(f"{sf}/events.parquet").count()


def test_clicks_meet_purchases(spark, sf, events, tmp_path):
    out = drained(live.clicks_to_purchases(events.where("event_type = 'click'"), events.where("event_type = 'purchase'"), late="60 days"), "met", tmp_path)
    from blockgraph.queries.registry import QUERIES

    assert sorted((r["click_id"], r["purchase_id"]) for r in out.collect()) == sorted((r["click_id"], r["purchase_id"]) for r in QUERIES["interval_click_purchase"](spark, sf).collect())


ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def test_counts_keep_state(spark, sf, events, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", ROCKS)
    try:
        out = drained(live.user_counts(events), "counts", tmp_path, "update")
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    real = spark.read.parquet(f"{sf}/events.parquet").groupBy("user_id").agg(F.count("*").alias("n"))
    assert out.where("NOT closed").groupBy("user_id").agg(F.max("n").alias("n")).exceptAll(real).isEmpty()
    assert out.where("NOT closed").groupBy("user_id").agg(F.max("n").alias("n")).count() == spark.read.parquet(f"{sf}/events.parquet").select("user_id").distinct().count()


def test_fold_in_by_batches(spark, sf, tmp_path):
    sizes = (2, 3, 5)
    edges = t.g4_rating(spark, sf).select("src", "dst", (F.col("cat") - 1).alias("cat"))
    edges.write.parquet(str(tmp_path / "edges"))
    _, right, cat = steps.starts(edges, sizes, 1)
    stream = spark.readStream.schema("src long, dst long, cat int").parquet(str(tmp_path / "edges"))
    q = stream.writeStream.foreachBatch(live.fold_in_batches(right, cat, sizes, str(tmp_path / "mem"))).option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.read.parquet(str(tmp_path / "mem")).count() == edges.select("src").distinct().count()


def test_late_rows_are_counted(spark, tmp_path):
    source = str(tmp_path / "late")
    row = lambda k, ts: spark.createDataFrame([(k, ts, 1, "view", 1.0, '{"k": 3}')], "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    for k, ts in enumerate(("2024-01-01 10:00:00", "2024-01-05 10:00:00", "2024-01-05 11:00:00", "2024-01-01 09:00:00")):
        row(k, ts).coalesce(1).write.mode("append").parquet(source)
        import time

        time.sleep(1.1)  # files are taken in the order of their times
    # the watermark that rows are held against is the one of the batch before
    limited = spark.readStream.schema(live.EVENTS).option("maxFilesPerTrigger", 1).parquet(source).withColumn("ts", F.col("ts").cast("timestamp"))
    counted = limited.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour"), "user_id").count()
    q = counted.writeStream.outputMode("update").format("memory").queryName("late").option("checkpointLocation", str(tmp_path / "ck-late")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert live.late_rows(q) == 1


def test_rate_source_makes_edges(spark, tmp_path):
    import time

    q = live.read_rate(spark, 50, 20).writeStream.format("memory").queryName("rate").option("checkpointLocation", str(tmp_path / "ck-rate")).trigger(processingTime="1 second").start()
    for _ in range(60):
        time.sleep(1)
        if spark.table("rate").count():
            break
    q.stop()
    rows = spark.table("rate").collect()
    assert rows and all(0 <= r["src"] < 20 and 0 <= r["dst"] < 20 for r in rows)
