"""Counter sketches for heavy hitters: per source, merged, and Spark's own."""

from __future__ import annotations

import json
from collections.abc import Iterator
from fractions import Fraction

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf


class CounterSketch:
    """At most ``capacity`` counters; a new key takes over a least counter with its count as error.

    Of n added, every key of more than n / capacity is held, and count - error <= true <= count. ``decay`` multiplies
    all counts after each ``decay_every`` rows, which forgets what was hot long ago.
    """

    def __init__(self, capacity: int, decay: float | None = None, decay_every: int = 1000):
        if capacity < 1:
            raise ValueError("a sketch needs a counter")
        self.capacity, self.decay, self.decay_every = capacity, decay, decay_every
        self.counts: dict = {}
        self.errors: dict = {}
        self.total = 0
        self._buckets: dict[int, dict] | None = None  # count -> keys in order of arrival; built once all counters are taken
        self._low = 0
        self._since = 0
        self.keep_errors = True  # where nothing reads them, they need not be kept

    def add(self, key, weight: int = 1) -> int:
        """Count a key; returns its count."""
        self.total += weight
        if self.decay is not None:
            self._since += 1
            if self._since >= self.decay_every:
                self._forget()
        counts = self.counts
        old = counts.get(key)
        if old is not None:
            new = counts[key] = old + weight
            if self._buckets is not None:
                self._move(key, old, new)
            return new
        if len(counts) < self.capacity:
            counts[key] = weight
            if self._buckets is not None:
                self._buckets.setdefault(weight, {})[key] = None
                self._low = min(self._low, weight)
            return weight
        if self._buckets is None:
            self._build()
        low = self._low
        bucket = self._buckets[low]
        victim = next(iter(bucket))
        del counts[victim], bucket[victim]
        self.errors.pop(victim, None)
        counts[key], self.errors[key] = low + weight, low
        self._buckets.setdefault(low + weight, {})[key] = None
        if not bucket:
            del self._buckets[low]
            self._lift(low, weight)
        return low + weight

    def hot_rows(self, keys: list, num: int, den: int) -> Iterator[int]:
        """Count keys one after another as ``add`` does, and stop at each row whose key then has at least the share num / den."""
        if self.decay is not None:
            for i, k in enumerate(keys):
                if self.add(k) * den >= num * self.total:
                    yield i
            return
        counts, errors, buckets, low, total, queue = self.counts, self.errors, self._buckets, self._low, self.total, None
        for i, k in enumerate(keys):
            total += 1
            old = counts.get(k)
            if old is None:
                if len(counts) < self.capacity:
                    counts[k] = new = 1
                    if buckets is not None:
                        buckets.setdefault(1, {})[k] = None
                        low, queue = 1, None
                    if den >= num * total:
                        self.total, self._low = total, low
                        yield i
                    continue
                if buckets is None:
                    self._build()
                    buckets, low = self._buckets, self._low
                bucket = buckets[low]
                if queue is None:
                    queue = iter(list(bucket))  # nothing arrives at the least count while it is the least
                for victim in queue:
                    if victim in bucket:
                        break
                del counts[victim], bucket[victim]
                old = low
                if self.keep_errors:
                    errors.pop(victim, None)
                    errors[k] = low
            elif buckets is not None:
                bucket = buckets[old]
                del bucket[k]
            counts[k] = new = old + 1
            if buckets is not None:
                held = buckets.get(new)
                if bucket:
                    if held is None:
                        buckets[new] = {k: None}
                    else:
                        held[k] = None
                else:
                    del buckets[old]
                    if held is None:
                        bucket[k] = None
                        buckets[new] = bucket
                    else:
                        held[k] = None
                    if old == low:
                        low, queue = new, None
            if new * den >= num * total:
                self.total, self._low = total, low
                yield i
        self.total, self._low = total, low

    def _build(self) -> None:
        self._buckets = {}
        for k, c in self.counts.items():
            self._buckets.setdefault(c, {})[k] = None
        self._low = min(self._buckets)

    def _move(self, key, old: int, new: int) -> None:
        bucket = self._buckets[old]
        del bucket[key]
        self._buckets.setdefault(new, {})[key] = None
        if not bucket:
            del self._buckets[old]
            if old == self._low:
                self._lift(old, new - old)

    def _lift(self, low: int, step: int) -> None:
        self._low = low + 1 if step == 1 else min(self._buckets)

    def _forget(self) -> None:
        self._since = 0
        kept = {k: int(c * self.decay) for k, c in self.counts.items()}
        self.counts = {k: c for k, c in kept.items() if c}
        self.errors = {k: e for k, e in ((k, int(e * self.decay)) for k, e in self.errors.items()) if e and k in self.counts}
        self.total = max(1, int(self.total * self.decay))
        self._buckets = None

    def items(self) -> list[tuple]:
        """``(key, count, error)``, most counted first, ties by key text."""
        return sorted(((k, c, self.errors.get(k, 0)) for k, c in self.counts.items()), key=lambda x: (-x[1], str(x[0])))

    def floor(self) -> int:
        """What a key that is not held may have been counted at most."""
        return min(self.counts.values()) if len(self.counts) >= self.capacity else 0

    def heavy(self, theta: Fraction | float, guaranteed: bool = False) -> list[tuple]:
        """Keys with at least the share theta of the messages."""
        t = Fraction(theta)
        return [(k, c, e) for k, c, e in self.items() if (c - e if guaranteed else c) * t.denominator >= t.numerator * self.total]

    def merge(self, other: CounterSketch) -> CounterSketch:
        """A sketch of both streams; a key that one side does not hold takes that side's floor as count and error."""
        out = CounterSketch(self.capacity)
        floors = self.floor(), other.floor()
        rows = []
        for k in self.counts.keys() | other.counts.keys():
            c = e = 0
            for s, f in ((self, floors[0]), (other, floors[1])):
                c += s.counts.get(k, f)
                e += s.errors.get(k, 0) if k in s.counts else f
            rows.append((k, c, e))
        rows.sort(key=lambda x: (-x[1], str(x[0])))
        for k, c, e in rows[: self.capacity]:
            out.counts[k] = c
            if e:
                out.errors[k] = e
        out.total = self.total + other.total
        return out


def default_capacity(theta: Fraction | float, factor: int = 4) -> int:
    """Counters for an error of at most theta / factor of the messages."""
    t = Fraction(theta)
    return -(-factor * t.denominator // t.numerator)


def sketch_per_source(sourced: DataFrame, capacity: int) -> DataFrame:
    """``(source_id, key, cnt, err, n_seen)`` of ``sourced(source_id, key, seq)``; one task holds one sketch at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(source, sketch: CounterSketch) -> pa.RecordBatch:
            rows = sketch.items()
            return pa.RecordBatch.from_arrays([pa.array([source] * len(rows), pa.int32()), pa.array([k for k, _, _ in rows], pa.string()), pa.array([c for _, c, _ in rows], pa.int64()), pa.array([e for _, _, e in rows], pa.int64()), pa.array([sketch.total] * len(rows), pa.int64())], ["source_id", "key", "cnt", "err", "n_seen"])

        now, sketch = None, None
        for b in batches:
            for source, key in zip(b.column("source_id").to_pylist(), b.column("key").to_pylist(), strict=True):
                if source != now:
                    if sketch is not None:
                        yield out(now, sketch)
                    now, sketch = source, CounterSketch(capacity)
                sketch.add(key)
        if sketch is not None:
            yield out(now, sketch)

    dealt = sourced.select("source_id", "seq", "key").repartition("source_id").sortWithinPartitions("source_id", "seq")
    return dealt.select("source_id", "key").mapInArrow(run, "source_id int, key string, cnt long, err long, n_seen long")


def merge_sketches(sketches: DataFrame, capacity: int) -> DataFrame:
    """``(key, cnt, err, n_seen)``: the sketches of all sources as one. A source that lacks a key adds its floor."""
    per = sketches.groupBy("source_id").agg(F.when(F.count("*") >= capacity, F.min("cnt")).otherwise(0).alias("floor"), F.first("n_seen").alias("n"))
    total = per.agg(F.sum("floor").alias("floors"), F.sum("n").alias("n_seen"))
    held = sketches.join(per.select("source_id", "floor"), "source_id").groupBy("key").agg(F.sum("cnt").alias("c"), F.sum("err").alias("e"), F.sum("floor").alias("own"))
    merged = held.join(F.broadcast(total)).select("key", (F.col("c") + F.col("floors") - F.col("own")).alias("cnt"), (F.col("e") + F.col("floors") - F.col("own")).alias("err"), "n_seen")
    return merged.orderBy(F.desc("cnt"), "key").limit(capacity)


def spilled_per_source(sourced: DataFrame, capacity: int) -> DataFrame:
    """``(source_id, key, cnt)`` of ``sourced(source_id, key)``: counters that lose nothing.

    A task holds ``capacity`` counters a source; when they are all taken, the lesser half leaves as rows and begins anew. A key may thus come
    in several rows, whose sum is its exact count, and since order does not matter, a source's rows need not be brought together.
    """
    if capacity < 2:
        raise ValueError("counters that spill by halves are two at least")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, dict] = {}

        def out(source: int, rows: list[tuple]) -> pa.RecordBatch:
            keys, counts = zip(*rows, strict=True)
            return pa.RecordBatch.from_arrays([pa.array([source] * len(keys), pa.int32()), pa.array(keys, pa.string()), pa.array(counts, pa.int64())], ["source_id", "key", "cnt"])

        for b in batches:
            told = pa.Table.from_batches([b]).group_by(["source_id", "key"]).aggregate([([], "count_all")])
            for source, key, n in zip(*(told.column(c).to_pylist() for c in ("source_id", "key", "count_all")), strict=True):
                counts = held.setdefault(source, {})
                if key not in counts and len(counts) >= capacity:
                    rows = sorted(counts.items(), key=lambda x: x[1])[: (capacity + 1) // 2]
                    for k, _ in rows:
                        del counts[k]
                    yield out(source, rows)
                counts[key] = counts.get(key, 0) + n
        for source, counts in held.items():
            if counts:
                yield out(source, list(counts.items()))

    return sourced.select("source_id", "key").mapInArrow(run, "source_id int, key string, cnt long")


def merge_spilled(spilled: DataFrame) -> DataFrame:
    """``(key, cnt, err, n_seen)`` of all sources: every key, exactly, so no error."""
    held = spilled.groupBy("key").agg(F.sum("cnt").alias("cnt"))
    total = held.agg(F.sum("cnt").alias("n_seen"))
    return held.join(F.broadcast(total)).select("key", "cnt", F.lit(0).cast("long").alias("err"), "n_seen")


def merge_udaf(capacity: int):
    """The merge as a grouped aggregate over sketch columns: JSON of ``[[key, count, error], ...]``."""

    @pandas_udf("string")
    def merged(source: pd.Series, key: pd.Series, cnt: pd.Series, err: pd.Series, n_seen: pd.Series) -> str:
        out = CounterSketch(capacity)
        for s in sorted(source.unique()):
            own, part = source == s, CounterSketch(capacity)
            part.counts = dict(zip(key[own], cnt[own].astype(int), strict=True))
            part.errors = {k: int(e) for k, e in zip(key[own], err[own], strict=True) if e}
            part.total = int(n_seen[own].iloc[0])
            out = out.merge(part)
        return json.dumps([[k, int(c), int(e)] for k, c, e in out.items()])

    return merged


def count_min_bound(msgs: DataFrame, keys: list[str], eps: float = 0.001, confidence: float = 0.99, seed: int = 7) -> list[tuple[str, int]]:
    """Upper bounds of the frequencies of given keys from one count-min sketch, built map-side and merged."""
    data = msgs.agg(F.count_min_sketch("key", F.lit(eps), F.lit(confidence), F.lit(seed)).alias("s")).first()["s"]
    jvm = msgs.sparkSession._jvm
    held = jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(bytearray(data))
    return [(k, held.estimateCount(k)) for k in keys]


def frequent_items(msgs: DataFrame, theta: Fraction | float) -> list[str]:
    """A superset of the keys with at least the share theta, from Spark's frequent-items sketch; may hold others too."""
    return list(msgs.freqItems(["key"], float(theta)).first()[0])


def native_head(msgs: DataFrame, theta: Fraction | float, max_items: int = 10_000) -> DataFrame:
    """Heavy keys by Spark's own mergeable top-k sketch: exact while ``max_items`` covers the keys."""
    t = Fraction(theta)
    k = min(max_items, -(-t.denominator // t.numerator))
    top = msgs.agg(F.expr(f"approx_top_k(key, {k}, {max_items})").alias("top"), F.count("*").alias("m"))
    rows = top.select("m", F.explode("top").alias("x")).select(F.col("x.item").alias("key"), F.col("x.count").alias("freq"), "m")
    return rows.where(F.col("freq") * t.denominator >= F.col("m") * t.numerator).select("key", "freq")
