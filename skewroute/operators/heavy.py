"""The head of a stream: exact, per window, and how it compares with sketches."""

from __future__ import annotations

from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from skewroute.functions import bounds


def frequencies(msgs: DataFrame) -> DataFrame:
    """``(key, freq)``; counted map-side first, so a hot key costs no more than any other."""
    return msgs.groupBy("key").agg(F.count("*").alias("freq"))


def exact_head(msgs: DataFrame, theta: Fraction | float) -> DataFrame:
    """``(key, freq, m, p, rank)`` of the keys with at least the share theta, hottest first, ties by key.

    At most 1 / theta keys pass, so what is ranked in one task is small by construction. The test is in integers.
    """
    t = Fraction(theta)
    counts = frequencies(msgs)
    total = counts.agg(F.sum("freq").alias("m"))
    head = counts.join(F.broadcast(total)).where(F.col("freq") * t.denominator >= F.col("m") * t.numerator)
    rank = F.row_number().over(Window.orderBy(F.desc("freq"), F.asc_nulls_first("key")))
    return head.select("key", "freq", "m", (F.col("freq") / F.col("m")).alias("p"), rank.alias("rank"))


def head_list(msgs: DataFrame, theta: Fraction | float) -> tuple[list[tuple], int]:
    """``[(key, freq)]`` hottest first, and the number of messages: at most 1 / theta rows reach the driver."""
    rows = exact_head(msgs, theta).select("key", "freq", "m").collect()
    return [(r["key"], r["freq"]) for r in rows], rows[0]["m"] if rows else 0


def head_by_window(msgs: DataFrame, every: str, theta: Fraction | float) -> DataFrame:
    """The head of each time window: ``(start, key, freq, p)``."""
    t = Fraction(theta)
    counts = msgs.groupBy(F.window(F.col("ts").cast("timestamp"), every).alias("w"), "key").agg(F.count("*").alias("freq"))
    # The total of a window is one row a window, joined rather than windowed: a window has as many rows as it has keys.
    totals = counts.groupBy("w").agg(F.sum("freq").alias("m"))
    heavy = counts.join(totals, "w").where(F.col("freq") * t.denominator >= F.col("m") * t.numerator)
    return heavy.select(F.col("w.start").alias("start"), "key", "freq", (F.col("freq") / F.col("m")).alias("p"))


def head_accuracy(exact: DataFrame, found: DataFrame, m: int) -> DataFrame:
    """Recall and precision of a found head ``(key, cnt)`` and its largest error as a share of the messages."""
    both = exact.select("key", "freq", F.lit(1).alias("a")).join(found.select("key", "cnt", F.lit(1).alias("b")), "key", "full")
    hits = F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull())
    return both.agg((hits / F.count("a")).alias("recall"), (hits / F.count("b")).alias("precision"), (F.max(F.abs(F.col("cnt") - F.col("freq"))) / m).alias("max_error"))


def head_size(shares: np.ndarray, theta: Fraction | float) -> int:
    """How many keys of a known distribution (descending shares) the head has."""
    return int((np.asarray(shares) >= float(theta)).sum())


def choice_constraints(head: DataFrame, n: int, eps: float = bounds.EPS) -> DataFrame:
    """``(d, h, lhs, rhs, ok)``: every prefix condition of every number of choices, as one declarative plan.

    ``head(rank, p)`` has at most 5 n rows at the default threshold; each meets the n - 2 candidate values of d by an
    explode, so the grid is bounded by the parameters alone.
    """
    order = Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    upto = head.select("rank", "p", F.sum("p").over(order).alias("upto"), F.sum("p").over(Window.partitionBy()).alias("all"), F.max("p").over(Window.partitionBy()).alias("p1"))
    grid = upto.select("*", F.explode(F.sequence(F.lit(2), F.lit(max(2, n - 1)))).alias("d")).where(F.col("d") >= F.greatest(F.lit(2), F.ceil(F.col("p1") * n)))
    b = bounds.expected_union(n, F.col("rank") * F.col("d"))
    lhs = F.col("upto") + F.pow(b / n, F.col("d")) * (F.col("all") - F.col("upto")) + F.pow(b / n, F.lit(2)) * (1 - F.col("all"))
    rhs = b * (1.0 / n + eps)
    return grid.select("d", F.col("rank").alias("h"), lhs.alias("lhs"), rhs.alias("rhs"), (lhs <= rhs).alias("ok"))


def pick_d(constraints: DataFrame, n: int) -> DataFrame:
    """``(d)``: the least number of choices whose prefixes all hold; n if there is none."""
    ok = constraints.groupBy("d").agg(F.bool_and("ok").alias("ok")).where("ok")
    return ok.agg(F.coalesce(F.min("d"), F.lit(n)).alias("d"))
