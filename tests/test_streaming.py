"""The live router gives what the batch router gives."""

import os
import time

import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from skewroute.operators.kernel import Scheme
from skewroute.operators.route import route
from skewroute.sources.tables import event_messages
from skewroute.streaming import router as live


@pytest.fixture()
def parts(folder, tmp_path):
    """Events in four files, consumed one a trigger in order."""
    table = pq.read_table(f"{folder}/events.parquet")
    cut = len(table) // 4
    (tmp_path / "events.parquet").mkdir()
    for i in range(4):
        path = tmp_path / "events.parquet" / f"events{i}.parquet"
        pq.write_table(table.slice(i * cut, cut if i < 3 else None), path)
        os.utime(path, (time.time() - 100 + i * 10,) * 2)
    return tmp_path


def messages(spark, parts):
    schema = spark.read.parquet(f"{parts}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{parts}/events.parquet")
    return stream.select(F.col("event_id").alias("seq"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_type").alias("key"))


@pytest.mark.parametrize("kind", ["two_choice", "tuned", "head_round_robin"])
def test_stream_equals_batch(spark, folder, parts, kind):
    out = live.route_stream(messages(spark, parts), Scheme(kind), 10, 3)
    live.start(out, f"{parts}/out", f"{parts}/checkpoint").awaitTermination()
    got = spark.read.parquet(f"{parts}/out").select("seq", "worker", "is_head", "n_choices")
    want = route(event_messages(spark, folder), kind, 10, 3).select("seq", "worker", "is_head", "n_choices")
    assert sorted(got.collect()) == sorted(want.collect())


def test_windows_of_workers_add_up(spark, folder, parts):
    routed = live.route_stream(live.prepare(messages(spark, parts), "1 hour"), Scheme("two_choice"), 4, 2)
    totals = live.window_totals(live.window_partials(routed, "1 day")).select(F.col("window.start").alias("start"), "key", "n")
    live.start(totals, f"{parts}/out", f"{parts}/checkpoint").awaitTermination()
    got = {(r["start"], r["key"]): r["n"] for r in spark.read.parquet(f"{parts}/out").collect()}
    want = {(r["s"], r["key"]): r["n"] for r in event_messages(spark, folder).groupBy(F.date_trunc("day", "ts").alias("s"), "key").agg(F.count("*").alias("n")).collect()}
    assert got and all(want[k] == n for k, n in got.items())  # windows the watermark has closed


def test_merged_head_between_batches(spark, folder, parts):
    merged = live.MergedHead(Scheme("any_worker"), 10, 3, f"{parts}/merged")
    merged.start(messages(spark, parts), f"{parts}/checkpoint").awaitTermination()
    rows = spark.read.parquet(f"{parts}/merged")
    assert rows.count() == event_messages(spark, folder).count()
    by = {r["batch"]: r["h"] for r in rows.groupBy("batch").agg(F.count_if("is_head").alias("h")).collect()}
    assert by[0] == 0 and all(by[b] > 0 for b in by if b)
    assert merged.sketch.total == rows.count()


@pytest.mark.parametrize("kind", ["any_worker", "head_round_robin", "tuned"])
def test_merged_head_survives_retries_and_restarts(spark, parts, kind):
    batches = [spark.read.parquet(f"{parts}/events.parquet/events{i}.parquet").select(F.col("event_id").alias("seq"), F.col("event_type").alias("key")) for i in range(3)]

    def rows(path):
        return sorted(map(tuple, spark.read.parquet(path).select("batch", "seq", "worker", "is_head", "n_choices").collect()))

    straight = live.MergedHead(Scheme(kind), 10, 3, f"{parts}/straight")
    for i, b in enumerate(batches):
        straight.on_batch(b, i)
    again = live.MergedHead(Scheme(kind), 10, 3, f"{parts}/again")
    for i, b in enumerate(batches):
        again.on_batch(b, i)
        again.on_batch(b, i)  # the batch was run twice
        again = live.MergedHead(Scheme(kind), 10, 3, f"{parts}/again")  # and the process started anew
    assert rows(f"{parts}/again") == rows(f"{parts}/straight")
    # Loads go on from batch to batch: the last state holds every message.
    again._load(spark, 3)
    assert sum(sum(load) for load, _ in again.loads.values()) == len(rows(f"{parts}/straight")) == again.sketch.total


def test_live_imbalance(spark, folder, parts):
    routed = live.route_stream(live.prepare(messages(spark, parts), "1 hour"), Scheme("two_choice"), 4, 2)
    live.start(live.live_imbalance(routed, 4, "10 days"), f"{parts}/out", f"{parts}/checkpoint").awaitTermination()
    got = {r["start"]: (r["messages"], round(r["imbalance"], 9)) for r in spark.read.parquet(f"{parts}/out").collect()}
    batch = route(event_messages(spark, folder), "two_choice", 4, 2).withColumn("w", F.window(F.col("ts").cast("timestamp"), "10 days").start)
    want = {}
    for r in batch.groupBy("w", "worker").count().collect():
        want.setdefault(r["w"], []).append(r["count"])
    assert got and all(got[w] == (sum(want[w]), round(max(want[w]) / sum(want[w]) - 0.25, 9)) for w in got)


def test_dedup_before_routing(spark, parts):
    twice = messages(spark, parts).union(messages(spark, parts))
    out = live.live_load(live.prepare(twice, "30 days", dedup=True).withColumn("worker", F.lit(0)))
    query = out.writeStream.format("memory").queryName("loads").outputMode("update").option("checkpointLocation", f"{parts}/c").trigger(availableNow=True).start()
    query.awaitTermination()
    assert spark.table("loads").agg(F.max("messages")).first()[0] == spark.read.parquet(f"{parts}/events.parquet").count()
