"""Whole parameter grids as one job: all streams beside each other, all scales and schemes over one ordered scan of each.

Only loads leave the kernel: a sender gives ``workers`` numbers for each point of the grid, whatever it has routed.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import replace
from fractions import Fraction
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from skewroute.functions import bounds
from skewroute.operators.kernel import MEMO_KEYS, Fleet, Scheme
from skewroute.sources import zipf

#: A point of a grid: number of workers and scheme. Points of one number are told apart by the schemes' labels.
Point = tuple[int, Scheme]


def zipf_streams(spark: SparkSession, m: int, grid: list[tuple[int, float]], seed: int = 7) -> DataFrame:
    """``(stream, seq, key)``: ``m`` messages for each number of keys and skew; a stream is named ``keys/z``.

    Draws are those of ``zipf_range``. The cuts of a stream are made where its rows are, not sent.
    """
    rows = spark.range(m).select(F.col("id").alias("seq"), zipf.uniform_bits(F.col("id").cast("string"), seed).alias("bits"), F.explode(_grid(grid)).alias("g"))
    return _drawn(rows)


def table_streams(spark: SparkSession, folder: str, grid: list[tuple[int, float]], table: str = "lineitem", seed: int = 7) -> DataFrame:
    """``(stream, seq, key)`` on the rows of a table, which are dealt over the streams by a hash of the row: each row is a message of one stream and draws its key there."""
    rows = spark.read.parquet(f"{folder}/{table}.parquet")
    row = zipf.lineitem_draw() if table == "lineitem" else F.col(rows.columns[0]).cast("string")
    dealt = rows.select(F.xxhash64(F.lit("seq"), *rows.columns).alias("seq"), zipf.uniform_bits(row, seed).alias("bits"), F.get(_grid(grid), F.pmod(F.xxhash64(*rows.columns), F.lit(len(grid))).cast("int")).alias("g"))
    return _drawn(dealt)


def _grid(grid: list[tuple[int, float]]) -> Column:
    return F.array(*(F.struct(F.lit(f"{k}/{z}").alias("stream"), F.lit(k).alias("k"), F.lit(z).alias("z"), F.lit(int(zipf.zipf_weights(k, z).sum())).alias("w")) for k, z in grid))


def _drawn(rows: DataFrame) -> DataFrame:
    """Keys of ``(seq, bits, g)`` by the cuts of each row's stream."""
    u = F.shiftright(F.col("bits") * F.col("g.w"), 32)

    def look_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cuts: dict[str, np.ndarray] = {}
        for b in batches:
            streams, u = b.column("stream").to_pylist(), b.column("u").to_numpy()
            first = np.flatnonzero([i == 0 or streams[i] != streams[i - 1] for i in range(len(streams))])
            keys = np.empty(len(u), np.int64)
            for lo, hi in zip(first, [*first[1:], len(u)], strict=True):
                if streams[lo] not in cuts:
                    cuts.clear()  # rows come stream by stream: one table at a time
                    cuts[streams[lo]] = np.cumsum(zipf.zipf_weights(int(b.column("k")[lo].as_py()), b.column("z")[lo].as_py()))
                keys[lo:hi] = np.searchsorted(cuts[streams[lo]], u[lo:hi], side="right") + 1
            yield pa.RecordBatch.from_arrays([b.column("stream"), b.column("seq"), pa.array(keys).cast(pa.string())], ["stream", "seq", "key"])

    drawn = rows.select(F.col("g.stream").alias("stream"), "seq", F.col("g.k").alias("k"), F.col("g.z").cast("double").alias("z"), u.alias("u"))
    return drawn.repartition("stream").sortWithinPartitions("stream", "seq").mapInArrow(look_up, "stream string, seq long, key string")


def side_by_side(streams: dict[str, DataFrame]) -> DataFrame:
    """Named message tables as one ``(stream, seq, key)``."""
    return reduce(DataFrame.unionByName, (df.select(F.lit(name).alias("stream"), F.col("seq").cast("long").alias("seq"), F.col("key").cast("string").alias("key")) for name, df in streams.items()))


def _bits(key: str | None, i: int) -> int:
    """The 32 bits that ``hash_choice`` of the md5 family takes its worker from."""
    return int.from_bytes(hashlib.md5(f"{i}:{chr(0) + 'null' if key is None else key}".encode()).digest()[:4])


def loads(streams: DataFrame, points: list[Point] | dict[str, list[Point]], sources: int = bounds.SOURCES, slices: Column | None = None, names: list[str] | None = None) -> DataFrame:
    """``(stream, slice, workers, scheme, worker, messages, head)``: what every worker got at each point (of a stream), and how much of it as head.

    ``slices`` numbers parts of a stream in their order (None: one, 0); messages are those of the part alone. A sender is a hash of the order, so no order has to be dense.
    ``names`` of all streams, where they are known, give every sender a partition of its own.
    Keys are hashed behind the exchange, once for each that a batch holds.
    """
    by_stream = points if isinstance(points, dict) else None
    names = list(points) if by_stream else names
    sent = streams.select("stream", "seq", "key", (F.lit(0) if slices is None else slices).cast("long").alias("slice"))
    dealt = sent.withColumn("source_id", F.pmod(F.xxhash64("seq"), F.lit(sources)).cast("int"))
    if names:
        place = (F.array_position(F.array(*map(F.lit, names)), F.col("stream")) - 1) * sources + F.col("source_id")
        dealt = dealt.repartitionById(len(names) * sources, place.cast("int"))
    else:
        dealt = dealt.repartition("stream", "source_id")
    dealt = dealt.sortWithinPartitions("stream", "source_id", "seq")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, fleet, held, hashed = None, None, {}, {}

        def out() -> Iterator[pa.RecordBatch]:
            rows = [(now[0], part, r.n, r.scheme.label, w, int(c), int(h)) for part, counts in sorted(held.items()) for r, (all_, head) in zip(fleet.routers, counts, strict=True) for w, (c, h) in enumerate(zip(all_, head, strict=True)) if c]
            kinds = (pa.string(), pa.int64(), pa.int32(), pa.string(), pa.int32(), pa.int64(), pa.int64())
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], ["stream", "slice", "workers", "scheme", "worker", "messages", "head"])

        for b in batches:
            stream, source, part = (b.column(c) for c in ("stream", "source_id", "slice"))
            code = stream.dictionary_encode()
            ids = np.column_stack([code.indices.to_numpy(), source.to_numpy(), part.to_numpy()])
            cuts = [0, *(np.flatnonzero((ids[1:] != ids[:-1]).any(axis=1)) + 1).tolist(), len(ids)]
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                if lo == hi:
                    continue
                at = (code.dictionary[int(ids[lo, 0])].as_py(), int(ids[lo, 1]))
                if at != now:
                    yield from out()
                    now, held = at, {}
                    fleet = Fleet(by_stream[now[0]] if by_stream else points, now[1])
                told = b.column("key").slice(lo, hi - lo).dictionary_encode("encode")
                own = told.dictionary.to_pylist()
                if len(hashed) > MEMO_KEYS:
                    hashed.clear()
                pairs = np.array([hashed.get(k) or hashed.setdefault(k, (_bits(k, 1), _bits(k, 2))) for k in own], np.int64).reshape(-1, 2)[told.indices.to_numpy()]
                before = [(list(r.load), list(h)) for r, h in zip(fleet.routers, fleet.heads, strict=True)]
                fleet.run([own[i] for i in told.indices.to_pylist()], pairs[:, 0], pairs[:, 1])
                n = int(ids[lo, 2])
                if n not in held:
                    held[n] = [(np.zeros(r.n, np.int64), np.zeros(r.n, np.int64)) for r in fleet.routers]
                for r, h, (load, head), (all_, heads) in zip(fleet.routers, fleet.heads, before, held[n], strict=True):
                    all_ += np.subtract(r.load, load)
                    heads += np.subtract(h, head)
        yield from out()

    found = dealt.mapInArrow(run, "stream string, slice long, workers int, scheme string, worker int, messages long, head long")
    return found.groupBy("stream", "slice", "workers", "scheme", "worker").agg(F.sum("messages").alias("messages"), F.sum("head").alias("head"))


def imbalances(found: DataFrame, by: tuple[str, ...] = ("stream", "workers", "scheme")) -> DataFrame:
    """``(by, messages, imbalance)``: the largest load less the mean."""
    total = found.groupBy(*dict.fromkeys([*by, "workers"]), "worker").agg(F.sum("messages").alias("c"))
    return total.groupBy(*dict.fromkeys([*by, "workers"])).agg(F.sum("c").alias("messages"), (F.max("c") / F.sum("c") - 1 / F.first("workers")).alias("imbalance"))


def imbalances_upto(found: DataFrame) -> DataFrame:
    """``(stream, workers, scheme, slice, imbalance)`` of all messages up to the end of each slice; absent workers count as empty."""
    parts = found.select("stream", "workers", "scheme", "slice").distinct()
    grid = parts.select("*", F.explode(F.sequence(F.lit(0), F.col("workers") - 1)).alias("worker"))
    key = ["stream", "workers", "scheme", "slice", "worker"]
    dense = grid.join(found.select(*key, "messages"), key, "left").fillna(0, ["messages"])
    upto = F.expr("sum(messages) OVER (PARTITION BY stream, workers, scheme, worker ORDER BY slice)")
    return dense.withColumn("upto", upto).groupBy("stream", "workers", "scheme", "slice").agg((F.max("upto") / F.sum("upto") - 1 / F.col("workers")).alias("imbalance"))


def wide(found: DataFrame, by: list[str], value: str = "imbalance") -> DataFrame:
    """One row a group, a column a scheme."""
    names = [r[0] for r in found.select("scheme").distinct().orderBy("scheme").collect()]
    return found.groupBy(*by).agg(*(F.max(F.when(F.col("scheme") == s, F.col(value))).alias(s) for s in names))


def every(schemes: list[Scheme] | tuple[str, ...], workers: list[int]) -> list[Point]:
    return [(n, s if isinstance(s, Scheme) else Scheme(s)) for n in workers for s in schemes]


def threshold_points(workers: list[int]) -> list[Point]:
    """Any worker and head round robin at each threshold from 2 / n down to 1 / (8 n); labels hold the threshold times n."""
    return [(n, Scheme(k, t, name=f"{k}@{float(t * n):.4f}")) for n in workers for k in ("any_worker", "head_round_robin") for t in bounds.theta_grid(n)]


def known_heads(streams: DataFrame, names: list[str], workers: list[int], theta=bounds.default_theta) -> dict[tuple[str, int], list[tuple[str, float]]]:
    """The exact head of every stream for each number of workers: one count of all keys, at most 1 / theta rows each reach the driver."""
    counts = streams.groupBy("stream", "key").agg(F.count("*").alias("freq"))
    total = counts.groupBy("stream").agg(F.sum("freq").alias("m"))
    least = min((Fraction(theta(n)) for n in workers))
    rows = counts.join(F.broadcast(total), "stream").where(F.col("freq") * least.denominator >= F.col("m") * least.numerator).collect()
    out = {}
    for name in names:
        own = sorted(((r["key"], r["freq"], r["m"]) for r in rows if r["stream"] == name), key=lambda x: (-x[1], x[0]))
        for n in workers:
            t = Fraction(theta(n))
            out[name, n] = [(k, f / m) for k, f, m in own if f * t.denominator >= m * t.numerator]
    return out


def minimum_choices(streams: DataFrame, names: list[str], workers: list[int], tolerance: float = bounds.EPS, sources: int = bounds.SOURCES) -> list[tuple]:
    """``(stream, workers, computed, minimum)``: the computed d, and the least d for head keys that balances as any worker does; one pass over all streams."""
    heads, points, computed = known_heads(streams, names, workers), {}, {}
    for name in names:
        points[name] = []
        for n in workers:
            keys, shares = zip(*heads[name, n], strict=True) if heads[name, n] else ((), ())
            p = np.array(shares)
            computed[name, n] = bounds.min_feasible_choices(p, max(0.0, 1 - float(p.sum())), n)
            base = Scheme("any_worker", head=tuple(keys))
            points[name] += [(n, replace(base, name="any")), *((n, replace(base, kind="fixed_head", d=d, name=str(d))) for d in range(2, n + 1))]
    found = {(r["stream"], r["workers"], r["scheme"]): r["imbalance"] for r in imbalances(loads(streams, points, sources)).collect()}
    out = []
    for name in names:
        for n in workers:
            any_ = found[name, n, "any"]
            out.append((name, n, computed[name, n], next((d for d in range(2, n + 1) if found[name, n, str(d)] <= any_ + tolerance), n)))
    return out


def analytic(spark: SparkSession, workers: list[int], z_grid: list[float], keys: int, messages: int = 10**7, eps: float = bounds.EPS) -> DataFrame:
    """``(workers, z, scheme, head_size, d, vs_two_choice, vs_shuffle)`` of exact Zipf shares: head, computed choices, and estimated state in percent more than
    the baselines. Shares, heads, prefix conditions and estimates are columns; the conditions meet at most 5 n head keys a point."""
    shares = spark.range(1, keys + 1).select(F.col("id").alias("rank"), F.explode(F.array(*map(F.lit, z_grid))).alias("z")).withColumn("w", F.pow("rank", -F.col("z")))
    shares = shares.join(F.broadcast(shares.groupBy("z").agg(F.sum("w").alias("total"))), "z").select("z", "rank", (F.col("w") / F.col("total")).alias("p"))
    each = shares.select("z", "rank", "p", F.explode(F.array(*map(F.lit, workers))).alias("workers"))
    head = each.where(F.col("p") >= 1 / (5.0 * F.col("workers")))
    picked = choices_of(head, eps)
    told = each.join(F.broadcast(picked), ["workers", "z"], "left").withColumn("d", F.coalesce("d", F.lit(2)))
    f, hot, n = F.rint(F.col("p") * messages), F.col("p") >= 1 / (5.0 * F.col("workers")), F.col("workers")
    state = lambda c: F.sum(F.least(f, F.when(hot, c).otherwise(F.lit(2))))
    one = told.groupBy("workers", "z").agg(F.count_if(hot).cast("int").alias("head_size"), F.first("d").alias("d"), F.max("p").alias("p1"), F.sum(F.least(f, F.lit(2))).alias("two"), F.sum(F.least(f, n)).alias("all"), state(F.col("d")).alias("tuned"), state(n).alias("any_worker"), state(n).alias("head_round_robin"))
    rows = one.unpivot(["workers", "z", "head_size", "d", "p1", "two", "all"], ["tuned", "any_worker", "head_round_robin"], "scheme", "own")
    return rows.select("workers", "z", "scheme", "head_size", "p1", F.col("d").cast("int").alias("d"), (100 * (F.col("own") / F.col("two") - 1)).alias("vs_two_choice"), (100 * (F.col("own") / F.col("all") - 1)).alias("vs_shuffle"))


def drawn_counts(spark: SparkSession, folder: str, keys: int, z_grid: list[float], seed: int = 7) -> DataFrame:
    """``(z, key, f)``: how often the rows of events draw each key at each skew. A row draws once for every skew, by the same bits; a task holds one counter a key and skew."""
    bits = spark.read.parquet(f"{folder}/events.parquet").select(zipf.uniform_bits(F.col("event_id").cast("string"), seed).alias("bits"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cuts = [np.cumsum(zipf.zipf_weights(keys, z)) for z in z_grid]
        seen = np.zeros((len(z_grid), keys), np.int64)
        for b in batches:
            u = b.column("bits").to_numpy()
            for cut, own in zip(cuts, seen, strict=True):
                own += np.bincount(np.searchsorted(cut, (u * cut[-1]) >> 32, side="right"), minlength=keys)
        for z, own in zip(z_grid, seen, strict=True):
            at = np.flatnonzero(own)
            yield pa.RecordBatch.from_arrays([pa.array([z] * len(at), pa.float64()), pa.array(at + 1, pa.int32()), pa.array(own[at])], ["z", "key", "f"])

    return bits.mapInArrow(count, "z double, key int, f long").groupBy("z", "key").agg(F.sum("f").alias("f"))


def measured_heads(counts: DataFrame, workers: list[int]) -> DataFrame:
    """``(workers, z, rank, key, f, m, p)`` of the keys with a fifth of a worker's share, hottest first: at most 5 n keys a point."""
    total = counts.groupBy("z").agg(F.sum("f").alias("m"))
    each = counts.join(F.broadcast(total), "z").select("*", F.explode(F.array(*map(F.lit, workers))).alias("workers"))
    rank = F.expr("row_number() OVER (PARTITION BY workers, z ORDER BY f DESC, key)")
    return each.where("f * 5 * workers >= m").select("workers", "z", rank.alias("rank"), "key", "f", "m", (F.col("f") / F.col("m")).alias("p"))


def measured(counts: DataFrame, workers: list[int], eps: float = bounds.EPS) -> DataFrame:
    """What ``analytic`` gives, of counted keys ``(z, key, f)``: state is what the very messages of a key can be spread over."""
    total = counts.groupBy("z").agg(F.sum("f").alias("m"), F.max("f").alias("top"))
    each = counts.join(F.broadcast(total), "z").select("*", F.explode(F.array(*map(F.lit, workers))).alias("workers"))
    told = each.join(F.broadcast(choices_of(measured_heads(counts, workers).select("workers", "z", "rank", "p"), eps)), ["workers", "z"], "left").withColumn("d", F.coalesce("d", F.lit(2)))
    f, n = F.col("f"), F.col("workers")
    hot = f * 5 * n >= F.col("m")
    state = lambda c: F.sum(F.least(f, F.when(hot, c).otherwise(F.lit(2))))
    one = told.groupBy("workers", "z").agg(F.count_if(hot).cast("int").alias("head_size"), F.first("d").alias("d"), F.max(F.col("top") / F.col("m")).alias("p1"), F.sum(F.least(f, F.lit(2))).alias("two"), F.sum(F.least(f, n)).alias("all"), state(F.col("d")).alias("tuned"), state(n).alias("any_worker"), state(n).alias("head_round_robin"))
    rows = one.unpivot(["workers", "z", "head_size", "d", "p1", "two", "all"], ["tuned", "any_worker", "head_round_robin"], "scheme", "own")
    return rows.select("workers", "z", "scheme", "head_size", "p1", F.col("d").cast("int").alias("d"), (100 * (F.col("own") / F.col("two") - 1)).alias("vs_two_choice"), (100 * (F.col("own") / F.col("all") - 1)).alias("vs_shuffle"))


def choices_of(head: DataFrame, eps: float = bounds.EPS) -> DataFrame:
    """``(workers, z, d)``: the least d whose prefix conditions hold, for every head ``(workers, z, rank, p)`` at once."""
    n, mine = F.col("workers"), "PARTITION BY workers, z"
    upto = head.selectExpr("*", f"sum(p) OVER ({mine} ORDER BY rank) AS upto", f"sum(p) OVER ({mine}) AS whole", f"max(p) OVER ({mine}) AS p1")
    grid = upto.select("*", F.explode(F.sequence(F.lit(2), F.greatest(F.lit(2), n - 1))).alias("d")).where((F.col("d") >= F.ceil(F.col("p1") * n)) & (F.col("d") < n))
    b = bounds.expected_union(n, F.col("rank") * F.col("d"))
    lhs = F.col("upto") + F.pow(b / n, F.col("d")) * (F.col("whole") - F.col("upto")) + F.pow(b / n, F.lit(2)) * (1 - F.col("whole"))
    ok = grid.groupBy("workers", "z", "d").agg(F.bool_and(lhs <= b * (1 / n + eps)).alias("ok")).where("ok").groupBy("workers", "z").agg(F.min("d").alias("least"))
    return head.select("workers", "z").distinct().join(ok, ["workers", "z"], "left").select("workers", "z", F.coalesce("least", n).alias("d"))


def exact_head_sizes(spark: SparkSession, workers: list[int], z_grid: list[float], keys: int) -> DataFrame:
    """``(workers, z, theta_n, head_size)`` at both ends of the range of thresholds."""
    shares = spark.range(1, keys + 1).select(F.explode(F.array(*map(F.lit, z_grid))).alias("z"), F.pow(F.col("id"), -F.col("z")).alias("w"))
    total = shares.groupBy("z").agg(F.sum("w").alias("total"))
    grid = F.array(*(F.struct(F.lit(n).alias("workers"), F.lit(t).alias("theta_n")) for n in workers for t in (2.0, 0.2)))
    each = shares.join(F.broadcast(total), "z").select("z", (F.col("w") / F.col("total")).alias("p"), F.inline(grid))
    return each.groupBy("workers", "z", "theta_n").agg(F.count_if(F.col("p") >= F.col("theta_n") / F.col("workers")).cast("int").alias("head_size"))


def saturated_throughput(found: DataFrame, service_us: int, source_per_second: float | None = None) -> DataFrame:
    """``(stream, scheme, per_second)`` of a run that its fullest worker holds back: senders stall when one queue is full, so all go at the pace of that worker,
    and never faster than they can send together (``source_per_second``; None: as fast as workers serve)."""
    worst = found.groupBy("stream", "scheme", "workers", "worker").agg(F.sum("messages").alias("c")).groupBy("stream", "scheme", "workers").agg((F.max("c") / F.sum("c")).alias("top"))
    pace = F.lit(1e6 / service_us) / F.col("top")
    return worst.select("stream", "scheme", (pace if source_per_second is None else F.least(pace, F.lit(float(source_per_second)))).alias("per_second"))
