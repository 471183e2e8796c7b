"""Live routing: the batch kernel as a stateful processor, worker aggregates in event-time windows, merged heads."""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from fractions import Fraction

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

import skewroute
from skewroute.functions import bounds
from skewroute.functions.hashing import hash_choice
from skewroute.operators import sketch
from skewroute.operators.kernel import Router, Scheme
from skewroute.operators.route import _known, route_many, with_source

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def read_messages(spark: SparkSession, folder: str, table: str, key: str, order: str, ts: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder's Parquet files of one table as a stream of messages; the schema is declared, not inferred."""
    schema = spark.read.parquet(f"{folder}/{table}.parquet").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", f"{table}*.parquet").option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return stream.select(F.col(order).cast("long").alias("seq"), F.col(ts).cast("timestamp").alias("ts"), F.col(key).cast("string").alias("key"))


def prepare(stream: DataFrame, lateness: str | None = None, dedup: bool = False) -> DataFrame:
    """Watermark, and drop messages sent twice, before routing."""
    out = stream.withWatermark("ts", lateness) if lateness else stream
    return out.dropDuplicatesWithinWatermark(["seq"]) if dedup else out


class RouterProcessor(StatefulProcessor):
    """One router a source. Its whole state (loads, sketch, choices) is one value of bounded size."""

    def __init__(self, scheme: Scheme, workers: int, family: str = "md5"):
        self.scheme, self.workers, self.family = scheme, workers, family

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("router", T.StructType([T.StructField("blob", T.BinaryType())]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        # A batch's rows may come in several parts: order them all before any is routed.
        df = pd.concat(list(rows), ignore_index=True).sort_values("seq", kind="stable")
        router = Router(self.scheme, self.workers, int(key[0]), self.family)
        if self.state.exists():
            router.restore(pickle.loads(self.state.get()[0]))
        w, h, d = router.run(df["key"].tolist(), df["choice1"].tolist(), df["choice2"].tolist())
        self.state.update((pickle.dumps(router.state()),))
        yield df.drop(columns=["choice1", "choice2"]).assign(worker=w, is_head=h, n_choices=d)

    def close(self) -> None:
        pass


def route_stream(stream: DataFrame, scheme: Scheme, workers: int, sources: int = bounds.SOURCES, family: str = "md5") -> DataFrame:
    """Route a stream ``(seq, ts, key)``. Between micro-batches a source's order is arrival, within one it is ``seq``.

    The number of workers is fixed for the life of a checkpoint: another one asks for a new checkpoint.
    """
    stream.sparkSession.conf.set("spark.sql.streaming.stateStore.providerClass", ROCKS)
    sourced = with_source(stream, sources).withColumns({"choice1": hash_choice("key", 1, workers, family), "choice2": hash_choice("key", 2, workers, family)})
    out = T.StructType([*(f for f in sourced.schema.fields if f.name not in ("choice1", "choice2")), T.StructField("worker", T.IntegerType()), T.StructField("is_head", T.BooleanType()), T.StructField("n_choices", T.IntegerType())])
    # The processor also starts in a process of the driver's host that has no package: it travels by value.
    cloudpickle.register_pickle_by_value(skewroute)
    try:
        return sourced.groupBy("source_id").transformWithStateInPandas(RouterProcessor(scheme, workers, family), out, "append", "none")
    finally:
        cloudpickle.unregister_pickle_by_value(skewroute)


def window_partials(routed: DataFrame, every: str) -> DataFrame:
    """Each worker's count of each key in each window."""
    return routed.groupBy(F.window("ts", every), "worker", "key").agg(F.count("*").alias("part"))


def window_totals(partials: DataFrame) -> DataFrame:
    """The parts of all workers put together."""
    return partials.groupBy("window", "key").agg(F.sum("part").alias("n"))


def window_counts(stream: DataFrame, kind: str, size: str, slide: str | None = None) -> DataFrame:
    """Counts of a stream by key in tumbling, sliding or session windows: ``(start, end, key, n)``."""
    w = F.session_window("ts", size) if kind == "session" else F.window("ts", size, slide) if kind == "sliding" else F.window("ts", size)
    return stream.groupBy(w.alias("w"), "key").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "key", "n")


def live_load(routed: DataFrame) -> DataFrame:
    """Messages at each worker so far (update mode)."""
    return routed.groupBy("worker").agg(F.count("*").alias("messages"))


def live_imbalance(routed: DataFrame, workers: int, every: str) -> DataFrame:
    """``(start, messages, imbalance)`` of each window: the counts of all workers side by side, one state row a window."""
    counts = [F.count_if(F.col("worker") == w) for w in range(workers)]
    peak = F.greatest(*counts) if workers > 1 else counts[0]
    seen = routed.groupBy(F.window("ts", every).alias("w")).agg(F.count("*").alias("messages"), peak.alias("top"))
    return seen.select(F.col("w.start").alias("start"), "messages", (F.col("top") / F.col("messages") - 1.0 / workers).alias("imbalance"))


def start(df: DataFrame, path: str, checkpoint: str, mode: str = "append"):
    """Run what is there and stop, into Parquet."""
    return df.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()


class MergedHead:
    """Route each micro-batch with the head of all batches before it and the loads that they have left, then add its sketches.

    A batch's rows go to a folder of its own (``batch=<id>``), and what the next batch needs (the merged sketch, the loads and
    cursors of all sources) to ``<path>-state``, both overwritten: a batch that is run again, by this process or after a
    restart, reads the state it read before and leaves the same rows once. At most ``capacity`` counters a source and
    ``sources * workers`` loads cross the driver in a batch.
    """

    def __init__(self, scheme: Scheme, workers: int, sources: int = bounds.SOURCES, path: str | None = None):
        self.base, self.workers, self.sources, self.path = scheme, workers, sources, path
        self.theta = scheme.theta or bounds.default_theta(workers)
        self.capacity = scheme.capacity or sketch.default_capacity(self.theta)
        self._fresh()

    def _fresh(self) -> None:
        self.sketch = sketch.CounterSketch(self.capacity)
        self.loads: dict[int, tuple[list[int], int]] = {}

    def _state_path(self, batch_id: int) -> str:
        return f"{self.path.rstrip('/')}-state/before={batch_id}"

    def _load(self, spark: SparkSession, batch_id: int) -> None:
        """The state as it was before a batch, whatever this object holds."""
        self._fresh()
        if batch_id:
            counts, errors, total, loads = pickle.loads(spark.read.parquet(self._state_path(batch_id)).first()["state"])
            self.sketch.counts, self.sketch.errors, self.sketch.total, self.loads = counts, errors, total, loads

    def _save(self, spark: SparkSession, batch_id: int) -> None:
        held = pickle.dumps((self.sketch.counts, self.sketch.errors, self.sketch.total, self.loads))
        spark.createDataFrame([(bytearray(held),)], "state binary").write.mode("overwrite").parquet(self._state_path(batch_id))

    def scheme(self) -> Scheme:
        held = self.sketch.heavy(Fraction(self.theta))
        return _known(self.base, [(k, c / self.sketch.total) for k, c, _ in held], self.workers)

    def on_batch(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        self._load(spark, batch_id)
        sourced, out = with_source(batch, self.sources), f"{self.path.rstrip('/')}/batch={batch_id}"
        scheme = self.scheme()
        route_many(sourced, [scheme], self.workers, self.sources, begin=self.loads).write.mode("overwrite").parquet(out)
        self._count(spark.read.parquet(out), scheme)
        for s in _sketches(sourced, self.capacity):
            self.sketch = self.sketch.merge(s)
        self._save(spark, batch_id + 1)

    def _count(self, routed: DataFrame, scheme: Scheme) -> None:
        turns = scheme.kind == "head_round_robin"
        loads: dict[int, tuple[list[int], int]] = {s: (list(load), cursor) for s, (load, cursor) in self.loads.items()}
        for r in routed.groupBy("source_id", "worker", "is_head").agg(F.count("*").alias("n")).collect():
            load, cursor = loads.get(r["source_id"], ([0] * self.workers, 0))
            if scheme.count_head_in_load or not (turns and r["is_head"]):
                load[r["worker"]] += r["n"]
            if turns and r["is_head"]:
                cursor = (cursor + r["n"]) % self.workers
            loads[r["source_id"]] = load, cursor
        self.loads = loads

    def start(self, stream: DataFrame, checkpoint: str):
        return stream.writeStream.foreachBatch(self.on_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _sketches(sourced: DataFrame, capacity: int) -> list[sketch.CounterSketch]:
    out: dict[int, sketch.CounterSketch] = {}
    for r in sketch.sketch_per_source(sourced, capacity).collect():
        s = out.setdefault(r["source_id"], sketch.CounterSketch(capacity))
        s.counts[r["key"]], s.total = r["cnt"], r["n_seen"]
        if r["err"]:
            s.errors[r["key"]] = r["err"]
    return list(out.values())
