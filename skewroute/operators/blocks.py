"""Routing for scale: block-granular kernel, a stateless salted plan, and a planned fractional one.

They are extensions: the exact kernel is the reference that their balance is measured against.
"""

from __future__ import annotations

import heapq
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skewroute.functions import bounds
from skewroute.functions.hashing import candidates, hash_choice
from skewroute.operators.kernel import Router, Scheme
from skewroute.operators.route import with_source


def water_fill(load: np.ndarray, count: int) -> np.ndarray:
    """How many of ``count`` equal messages each worker gets so that the fullest stays lowest; ties to the first."""
    order = np.argsort(load, kind="stable")
    sorted_ = load[order]
    k = np.arange(1, len(load) + 1)
    need = sorted_ * k - np.cumsum(sorted_)  # to lift the first k to the level of the k-th
    m = int(np.searchsorted(need, count, side="right"))
    level, rest = divmod(int(sorted_[:m].sum()) + count, m)
    out = np.zeros(len(load), np.int64)
    out[order[:m]] = level - sorted_[:m]
    out[order[:rest]] += 1
    return out


def route_blocks(msgs: DataFrame, scheme: Scheme, workers: int, block: int, sources: int = bounds.SOURCES, order: str = "seq", dense: bool = True, family: str = "md5") -> DataFrame:
    """The scheme in blocks of ``block`` rows: hot keys of a block are poured over their workers at once, the other
    keys choose by the loads at its start. ``block=1`` is the exact kernel. Needs a known head.
    """
    if scheme.head is None and scheme.kind != "two_choice":
        raise ValueError("blocks take a known head")
    sourced = with_source(msgs, sources, order, dense)
    c = [hash_choice("key", i, workers, family).alias(f"_c{i}") for i in (1, 2)]
    dealt = sourced.select("*", *c).repartitionById(sources, F.col("source_id")).sortWithinPartitions("source_id", order)
    names, hot = sourced.columns, {k: i for i, k in enumerate(scheme.head or ())}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, router, load = None, None, None
        for b in batches:
            ids, keys = b.column("source_id").to_numpy(), b.column("key").to_pylist()
            code = np.fromiter((hot.get(k, -1) for k in keys), np.int64, len(keys))
            c1, c2 = b.column("_c1").to_numpy(), b.column("_c2").to_numpy()
            w, d = np.empty(len(keys), np.int32), np.full(len(keys), 2, np.int32)
            cuts = [0, *(np.flatnonzero(ids[1:] != ids[:-1]) + 1).tolist(), len(ids)]
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                if lo < hi and ids[lo] != now:
                    now, router, load = ids[lo], Router(scheme, workers, int(ids[lo]), family), np.zeros(workers, np.int64)
                for s in range(lo, hi, block):
                    e = min(hi, s + block)
                    part = code[s:e]
                    cold = np.flatnonzero(part < 0) + s
                    w[cold] = np.where(load[c2[cold]] < load[c1[cold]], c2[cold], c1[cold])
                    load += np.bincount(w[cold], minlength=workers)
                    for k in np.unique(part[part >= 0]):
                        rows = np.flatnonzero(part == k) + s
                        key = scheme.head[k]
                        many = workers if scheme.kind in ("any_worker", "head_round_robin") else min(scheme.d or 2, workers)
                        where = np.arange(workers) if many >= workers else np.array(list(dict.fromkeys(router.candidates(key, many, (int(c1[rows[0]]), int(c2[rows[0]]))))))
                        each = water_fill(load[where], len(rows))
                        w[rows], d[rows] = np.repeat(where, each), many
                        load[where] += each
            yield pa.RecordBatch.from_arrays([*(b.column(x) for x in names), pa.array(w), pa.array(code >= 0), pa.array(d)], [*names, "worker", "is_head", "n_choices"])

    return dealt.mapInArrow(run, T.StructType([*sourced.schema.fields, T.StructField("worker", T.IntegerType()), T.StructField("is_head", T.BooleanType()), T.StructField("n_choices", T.IntegerType())]))


def salted_plan(msgs: DataFrame, head: DataFrame, d: int, workers: int, order: str = "seq", family: str = "xx") -> DataFrame:
    """No state at all: a row picks among its key's choices by a hash of its own. One broadcast join of the head."""
    told = msgs.join(F.broadcast(head.select("key", F.lit(True).alias("_hot"))), "key", "left")
    many = F.when(F.col("_hot"), F.lit(d)).otherwise(F.lit(2))
    pick = F.pmod(F.xxhash64(F.lit("salt"), F.col(order)), many).cast("int")
    worker = F.when(F.col("_hot") & F.lit(d >= workers), pick) if d >= workers else None
    hashed = hash_choice("key", pick + 1, workers, family)
    worker = hashed if worker is None else worker.otherwise(hashed)
    return told.select(*msgs.columns, worker.cast("int").alias("worker"), F.coalesce("_hot", F.lit(False)).alias("is_head"), many.alias("n_choices"))


def plan_fractions(cold: dict[tuple[int, int], int], hot: dict[str, int], choices: dict[str, list[int]], workers: int) -> tuple[dict[tuple[int, int], float], dict[str, list[float]]]:
    """Shares for each pair of candidates and each hot key that level the load: pairs first, then hot keys, biggest last."""
    load = np.zeros(workers)
    share: dict[tuple[int, int], float] = {}
    pairs = sorted(cold.items(), key=lambda x: -x[1])
    for (a, b), n in pairs:
        load[a] += n / 2
        load[b] += n / 2
        share[a, b] = 0.5
    for _ in range(8):  # a few sweeps settle the pairs
        for (a, b), n in pairs:
            load[a] -= n * share[a, b]
            load[b] -= n * (1 - share[a, b])
            share[a, b] = 1.0 if a == b else float(np.clip((load[b] - load[a] + n) / (2 * n), 0, 1))
            load[a] += n * share[a, b]
            load[b] += n * (1 - share[a, b])
    weights: dict[str, list[float]] = defaultdict(list)
    for key, n in sorted(hot.items(), key=lambda x: x[1]):
        where = list(dict.fromkeys(choices[key]))
        heap = [(load[w], w) for w in where]
        heapq.heapify(heap)
        give = dict.fromkeys(where, 0.0)
        for _ in range(64):
            low, w = heapq.heappop(heap)
            give[w] += n / 64
            heapq.heappush(heap, (low + n / 64, w))
        for w in where:
            load[w] += give[w]
        weights[key] = [give[w] / n for w in where]
    return share, weights


def planned_routing(msgs: DataFrame, head: DataFrame, d: int, workers: int, order: str = "seq", family: str = "md5") -> DataFrame:
    """Two scans: a histogram of candidate pairs (at most n^2 cells) and of the head, fractions made on the driver, and
    rows that pick by a hash against them. No sequential state, balance by count.
    """
    spark = msgs.sparkSession
    both = msgs.withColumns({"_c1": hash_choice("key", 1, workers, family), "_c2": hash_choice("key", 2, workers, family)})
    many = F.sequence(F.lit(0), F.lit(workers - 1)) if d >= workers else candidates("key", d, workers, family)
    top = {r["key"]: (r["freq"], r["c"]) for r in head.select("key", "freq", many.alias("c")).collect()}
    cold = both.join(F.broadcast(head.select("key")), "key", "left_anti").groupBy("_c1", "_c2").agg(F.count("*").alias("n")).collect()
    share, weights = plan_fractions({(r["_c1"], r["_c2"]): r["n"] for r in cold}, {k: f for k, (f, _) in top.items()}, {k: c for k, (_, c) in top.items()}, workers)
    pairs = spark.createDataFrame([(a, b, s) for (a, b), s in share.items()] or [(-1, -1, 0.0)], "_c1 int, _c2 int, _share double")
    keys = spark.createDataFrame([(k, list(dict.fromkeys(c)), np.cumsum(weights[k]).tolist()) for k, (_, c) in top.items()], "key string, _to array<int>, _upto array<double>")
    u = F.pmod(F.xxhash64(F.lit("plan"), F.col(order)), F.lit(1 << 30)) / float(1 << 30)
    told = both.join(F.broadcast(keys), "key", "left").join(F.broadcast(pairs), ["_c1", "_c2"], "left").withColumn("_u", u)
    slot = F.least(F.size(F.filter("_upto", lambda x: x <= F.col("_u"))) + 1, F.size("_to"))
    cold_pick = F.when(F.col("_u") < F.col("_share"), F.col("_c1")).otherwise(F.col("_c2"))
    hot = F.col("_to").isNotNull()
    return told.select(*msgs.columns, F.when(hot, F.element_at("_to", slot)).otherwise(cold_pick).cast("int").alias("worker"), hot.alias("is_head"), F.when(hot, F.lit(d)).otherwise(2).alias("n_choices"))


def throughput_probe(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """A stand-in for costly per-row work at workers: some arithmetic a row, and the count."""
    n = 0
    for b in batches:
        for key in b["key"]:
            x = hash(key)
            for _ in range(200):
                x = (x * 6364136223846793005 + 1442695040888963407) & 0xFFFFFFFFFFFFFFFF
            n += 1 + (x & 0)
    yield pd.DataFrame({"n": [n]})
