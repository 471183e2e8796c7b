"""Measures of routed streams: load, imbalance, replicated state, merge cost, and the formulas they are compared with.

``by`` columns (a scheme, a data set) split every measure, so that a whole comparison is one aggregate.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F

from skewroute.operators import heavy


def worker_load(routed: DataFrame, n: int, by: list[str] | None = None) -> DataFrame:
    """``(by, worker, messages, load)``: share of the messages at each of n workers, absent workers with 0."""
    by = by or []
    counts = routed.groupBy(*by, "worker").agg(F.count("*").alias("messages"))
    groups = counts.groupBy(*by).agg(F.sum("messages").alias("m"))
    # The grid is n rows a group: an explode of the groups, no join of messages.
    grid = groups.select("*", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("worker"))
    full = grid.join(counts, [*by, "worker"], "left").select(*by, "worker", F.coalesce("messages", F.lit(0)).cast("long").alias("messages"), "m")
    return full.withColumn("load", F.col("messages") / F.col("m")).drop("m")


def imbalance(routed: DataFrame, n: int, by: list[str] | None = None) -> DataFrame:
    """``(by, imbalance)``: the largest load less the mean, which is 1 / n whatever happens."""
    by = by or []
    counts = routed.groupBy(*by, "worker").agg(F.count("*").alias("c"))
    return counts.groupBy(*by).agg((F.max("c") / F.sum("c") - 1.0 / n).alias("imbalance"))


def imbalance_over_time(routed: DataFrame, n: int, bucket: Column, by: list[str] | None = None) -> DataFrame:
    """``(by, bucket, imbalance)`` of all messages up to the end of each bucket."""
    by = by or []
    counts = routed.groupBy(*by, bucket.alias("bucket"), "worker").agg(F.count("*").alias("c"))
    buckets = counts.select(*by, "bucket").distinct()
    grid = buckets.select("*", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("worker"))
    dense = grid.join(counts, [*by, "bucket", "worker"], "left").fillna(0, ["c"])
    upto = F.sum("c").over(Window.partitionBy(*by, "worker").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0))
    return dense.withColumn("upto", upto).groupBy(*by, "bucket").agg((F.max("upto") / F.sum("upto") - 1.0 / n).alias("imbalance"))


def mean_imbalance(series: DataFrame, by: list[str] | None = None) -> DataFrame:
    """``(by, mean_imbalance, final_imbalance)`` of an imbalance series."""
    return series.groupBy(*(by or [])).agg(F.avg("imbalance").alias("mean_imbalance"), F.max_by("imbalance", "bucket").alias("final_imbalance"))


def moving_imbalance(routed: DataFrame, n: int, rows: int, order: str = "seq") -> DataFrame:
    """``(slice, imbalance)`` of each slice of ``rows`` consecutive messages by a dense order."""
    counts = routed.groupBy(F.floor(F.col(order) / rows).alias("slice"), "worker").agg(F.count("*").alias("c"))
    return counts.groupBy("slice").agg((F.max("c") / F.sum("c") - 1.0 / n).alias("imbalance"))


def load_by_part(routed: DataFrame, n: int, by: list[str] | None = None) -> DataFrame:
    """``(by, worker, head_load, tail_load)`` with zero rows for workers that got nothing."""
    by = by or []
    counts = routed.groupBy(*by, "worker").agg(F.count_if("is_head").alias("h"), F.count_if(~F.col("is_head")).alias("t"))
    groups = counts.groupBy(*by).agg(F.sum(F.col("h") + F.col("t")).alias("m"))
    grid = groups.select("*", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("worker"))
    return grid.join(counts, [*by, "worker"], "left").select(*by, "worker", (F.coalesce("h", F.lit(0)) / F.col("m")).alias("head_load"), (F.coalesce("t", F.lit(0)) / F.col("m")).alias("tail_load"))


def replicas(routed: DataFrame, by: list[str] | None = None, approximate: bool = False) -> DataFrame:
    """``(by, replicas)``: how many (key, worker) pairs hold state. Approximate: one sketch a worker, summed."""
    by = by or []
    if approximate:
        per = routed.groupBy(*by, "worker").agg(F.approx_count_distinct("key", 0.01).alias("r"))
        return per.groupBy(*by).agg(F.sum("r").alias("replicas"))
    return routed.select(*by, "key", "worker").distinct().groupBy(*by).agg(F.count("*").alias("replicas"))


def merge_fan_in(routed: DataFrame, by: list[str] | None = None) -> DataFrame:
    """``(by, avg_fan_in, max_fan_in)``: partial states to merge a key."""
    by = by or []
    per = routed.select(*by, "key", "worker").distinct().groupBy(*by, "key").agg(F.count("*").alias("w"))
    return per.groupBy(*by).agg(F.avg("w").alias("avg_fan_in"), F.max("w").alias("max_fan_in"))


def memory_bound(scheme: str, keys: int, head: int, n: int, d: int = 2) -> int:
    """Most state units a scheme may hold: one unit a key and worker."""
    if scheme == "key_grouping":
        return keys
    if scheme == "shuffle_grouping":
        return n * keys
    each = {"two_choice": 2, "tuned": min(d, n), "any_worker": n, "head_round_robin": n}[scheme]
    return each * head + 2 * (keys - head)


def memory_estimate(freqs: DataFrame, n: int, head: DataFrame, d: int) -> DataFrame:
    """``(scheme, estimate)`` from key frequencies: a key cannot be at more workers than it has messages."""
    marked = freqs.join(F.broadcast(head.select("key", F.lit(True).alias("hot"))), "key", "left")

    def at(hot: int) -> Column:
        return F.sum(F.least(F.col("freq"), F.when(F.col("hot"), F.lit(hot)).otherwise(F.lit(2))))

    one = marked.agg(F.count("*").alias("key_grouping"), at(2).alias("two_choice"), at(min(d, n)).alias("tuned"), at(n).alias("any_worker"), at(n).alias("head_round_robin"), F.sum(F.least(F.col("freq"), F.lit(n))).alias("shuffle_grouping"))
    return one.unpivot([], list(one.columns), "scheme", "estimate")


def memory_ratio(estimates: DataFrame) -> DataFrame:
    """``(scheme, vs_two_choice, vs_shuffle)``: percent more (or less) than these two."""
    base = estimates.agg(F.max(F.when(F.col("scheme") == "two_choice", F.col("estimate"))).alias("two"), F.max(F.when(F.col("scheme") == "shuffle_grouping", F.col("estimate"))).alias("all"))
    return estimates.join(F.broadcast(base)).select("scheme", (100 * (F.col("estimate") / F.col("two") - 1)).alias("vs_two_choice"), (100 * (F.col("estimate") / F.col("all") - 1)).alias("vs_shuffle"))


def load_view_gap(routed: DataFrame, n: int) -> DataFrame:
    """``(source_id, gap)``: how far a source's view of any worker's load is from the true one."""
    own = worker_load(routed, n, ["source_id"]).withColumnRenamed("load", "mine").drop("messages")
    true = worker_load(routed, n).select("worker", "load")
    return own.join(F.broadcast(true), "worker").groupBy("source_id").agg(F.max(F.abs(F.col("mine") - F.col("load"))).alias("gap"))


def mixture_bound(routed: DataFrame, n: int) -> DataFrame:
    """``(imbalance, bound)``: the true imbalance never exceeds the message-weighted mean of the sources' own.

    The largest load of a mixture is at most the mixture of the largest loads.
    """
    counts = routed.groupBy("source_id", "worker").agg(F.count("*").alias("c"))
    per = counts.groupBy("source_id").agg(F.max("c").alias("top"), F.sum("c").alias("m"))
    bound = per.agg((F.sum("top") / F.sum("m") - 1.0 / n).alias("bound"))
    return imbalance(routed, n).join(F.broadcast(bound))


def load_dispersion(routed: DataFrame, n: int, by: list[str] | None = None) -> DataFrame:
    """``(by, deviation, peak_to_mean)`` of worker loads."""
    load = worker_load(routed, n, by)
    return load.groupBy(*(by or [])).agg(F.stddev_pop("load").alias("deviation"), (F.max("load") * n).alias("peak_to_mean"))


def choice_gap(computed: int, minimum: int, n: int, spark: SparkSession) -> DataFrame:
    """``(computed, minimum, gap, fraction)``: a computed number of choices beside the least that works."""
    return spark.createDataFrame([(computed, minimum, computed - minimum, computed / n)], "computed int, minimum int, gap int, fraction double")


def replica_floor(routed: DataFrame, n: int) -> DataFrame:
    """``(floor)``: no routing with these replicas can be below the hottest key's share a worker, less the mean."""
    total = heavy.frequencies(routed).agg(F.sum("freq").alias("m"))
    per = routed.groupBy("key").agg(F.count("*").alias("f"), F.countDistinct("worker").alias("w"))
    return per.join(F.broadcast(total)).agg((F.max(F.col("f") / F.col("w") / F.col("m")) - 1.0 / n).alias("floor"))


def observed(routed: DataFrame, n: int) -> tuple[DataFrame, Observation]:
    """The routed rows with their count and the loads of all workers observed as they pass."""
    seen = Observation("load")
    counts = [F.count_if(F.col("worker") == w).alias(f"w{w}") for w in range(n)]
    return routed.observe(seen, F.count("*").alias("m"), *counts), seen


def compare_routings(a: DataFrame, b: DataFrame) -> DataFrame:
    """``(source_id, rows, differing)`` of two routings of one stream, a source's rows side by side in one group.

    Groups are held whole by a task: for tests and small streams.
    """

    def beside(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        both = left.merge(right, on=["source_id", "seq"], how="outer", suffixes=("", "_b"))
        differing = int((both["worker"] != both["worker_b"]).sum())
        return pd.DataFrame({"source_id": [int(both["source_id"].iloc[0])], "rows": [len(both)], "differing": [differing]})

    keep = ["source_id", "seq", "worker"]
    return a.select(keep).groupBy("source_id").cogroup(b.select(keep).groupBy("source_id")).applyInPandas(beside, "source_id int, rows long, differing long")
