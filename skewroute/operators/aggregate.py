"""What routed streams are for: placing, partial aggregates at workers, their reconciliation, and skew-proof joins."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skewroute.functions.hashing import candidates, hash_choice

#: Aggregates that split: how a worker's part is made, and how parts make the whole.
_PARTS: dict[str, tuple[Callable[[str], list[Column]], Callable[[str], Column]]] = {
    "count": (lambda c: [F.count(c).alias(f"count_{c}")], lambda c: F.sum(f"count_{c}")),
    "sum": (lambda c: [F.sum(c).alias(f"sum_{c}")], lambda c: F.sum(f"sum_{c}")),
    "min": (lambda c: [F.min(c).alias(f"min_{c}")], lambda c: F.min(f"min_{c}")),
    "max": (lambda c: [F.max(c).alias(f"max_{c}")], lambda c: F.max(f"max_{c}")),
    "avg": (lambda c: [F.sum(c).alias(f"avgs_{c}"), F.count(c).alias(f"avgn_{c}")], lambda c: F.sum(f"avgs_{c}") / F.sum(f"avgn_{c}")),
    "var_pop": (lambda c: [F.count(c).alias(f"vn_{c}"), F.avg(c).alias(f"va_{c}"), F.var_pop(c).alias(f"vv_{c}")], lambda c: _pooled(f"vn_{c}", f"va_{c}", f"vv_{c}")),
    "collect": (lambda c: [F.collect_list(c).alias(f"list_{c}")], lambda c: F.array_sort(F.flatten(F.collect_list(f"list_{c}")))),
    "distinct": (lambda c: [F.collect_set(c).alias(f"set_{c}")], lambda c: F.size(F.array_distinct(F.flatten(F.collect_list(f"set_{c}")))).cast("long")),
    "approx_distinct": (lambda c: [F.hll_sketch_agg(c).alias(f"hll_{c}")], lambda c: F.hll_sketch_estimate(F.hll_union_agg(f"hll_{c}"))),
}


def _pooled(n: str, mean: str, var: str) -> Column:
    """Population variance of parts: mean of variances plus variance of means, weighed by size."""
    total = F.sum(n)
    center = F.sum(F.col(n) * F.col(mean)) / total
    return F.sum(F.col(n) * (F.col(var) + F.col(mean) * F.col(mean))) / total - center * center


def place(routed: DataFrame, n: int) -> DataFrame:
    """Worker i is partition i; the aggregate by (worker, key) that follows needs no further exchange."""
    return routed.repartitionById(n, F.col("worker"))


def partial_agg(placed: DataFrame, aggs: dict[str, tuple[str, str]]) -> DataFrame:
    """``(worker, key, parts)`` of ``{output: (aggregate, column)}``."""
    return placed.groupBy("worker", "key").agg(*{str(c): c for kind, col in aggs.values() for c in _PARTS[kind][0](col)}.values())


def merge_agg(partials: DataFrame, aggs: dict[str, tuple[str, str]]) -> DataFrame:
    """``(key, outputs)``: as many parts meet as the key has replicas."""
    return partials.groupBy("key").agg(*(_PARTS[kind][1](col).alias(out) for out, (kind, col) in aggs.items()))


def balanced_agg(routed: DataFrame, n: int, aggs: dict[str, tuple[str, str]]) -> DataFrame:
    """The two-phase aggregate of a routed stream; equals the plain one for every scheme."""
    return merge_agg(partial_agg(place(routed, n), aggs), aggs)


def combined_agg(routed: DataFrame, aggs: dict[str, tuple[str, str]]) -> DataFrame:
    """The same where rows are too many to be sent: every task combines what it has for a worker and key, and only that is exchanged. Workers' parts meet by (worker, key)."""
    return merge_agg(partial_agg(routed, aggs), aggs)


def apply_worker(routed: DataFrame, n: int, fn: Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]], schema: str) -> DataFrame:
    """Costly work on each worker's rows, in their partition."""
    return place(routed, n).mapInPandas(fn, schema)


def balanced_join(big: DataFrame, small: DataFrame, on: str, hot: list, n: int, spread: int, how: str = "inner", family: str = "xx", salt: Column | None = None) -> DataFrame:
    """Join a skewed table: rows of hot keys go to one of ``spread`` places by a hash of the row, rows of the other
    side are copied to all places of their key. ``hot`` is the head, bounded by its threshold; the rest joins as ever.
    """
    if how not in ("inner", "left"):
        raise ValueError("inner or left")
    is_hot = F.col(on).isin(hot) if hot else F.lit(False)
    at = F.pmod(salt if salt is not None else F.xxhash64(*big.columns), F.lit(spread)).cast("int")
    dealt = big.withColumn("_place", F.when(F.coalesce(is_hot, F.lit(False)), at).otherwise(0))
    copies = small.withColumn("_place", F.explode(F.when(is_hot, F.sequence(F.lit(0), F.lit(spread - 1))).otherwise(F.array(F.lit(0)))))
    return dealt.join(copies, [on, "_place"], how).drop("_place")


def candidate_join(routed: DataFrame, small: DataFrame, n: int, d: int, head: DataFrame, family: str = "md5") -> DataFrame:
    """Join a routed stream at its workers: the other side is copied to every worker its key may have been sent to."""
    told = small.join(F.broadcast(head.select("key", F.lit(True).alias("_hot"))), "key", "left")
    everywhere = F.sequence(F.lit(0), F.lit(n - 1))
    two = F.array_distinct(candidates("key", 2, n, family))
    more = everywhere if d >= n else F.array_distinct(F.array_union(two, F.transform(F.sequence(F.lit(1), F.lit(d)), lambda i: hash_choice("key", i, n, family))))
    copies = told.withColumn("worker", F.explode(F.when(F.col("_hot"), more).otherwise(two))).drop("_hot")
    return routed.join(copies, ["worker", "key"])
