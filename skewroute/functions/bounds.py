"""Thresholds, bounds and the least feasible number of choices."""

from __future__ import annotations

import math
from fractions import Fraction

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

EPS = 1e-4
SOURCES = 5


def default_theta(n: int) -> Fraction:
    """A key belongs to the head from this share of the messages on."""
    return Fraction(1, 5 * n)


def theta_grid(n: int) -> list[Fraction]:
    """The thresholds that experiments sweep, from twice a worker's share down to an eighth of it, and the default."""
    return [Fraction(2, n), Fraction(1, n), Fraction(1, 2 * n), Fraction(1, 4 * n), Fraction(1, 5 * n), Fraction(1, 8 * n)]


def two_choice_regime(p1: Column, n: int) -> Column:
    """``fails``: the hottest key alone overfills two workers; ``safe``: no key is above the safe share; else ``grey``."""
    return F.when(p1 > 2.0 / n, "fails").when(p1 <= 1.0 / (5 * n), "safe").otherwise("grey")


def two_choice_floor(p1: Column, n: int) -> Column:
    """The imbalance that two choices cannot go below."""
    return F.greatest(F.lit(0.0), p1 / 2 - 1.0 / n)


def expected_union(n: int | float | Column, throws: int | Column):
    """Expected number of distinct workers hit by uniform throws."""
    if isinstance(throws, Column) or isinstance(n, Column):
        n = n if isinstance(n, Column) else F.lit(float(n))
        return n - n * F.pow((n - 1) / n, throws)
    return n - n * ((n - 1) / n) ** throws


def start_choices(p1: float, n: int) -> int:
    return max(2, math.ceil(p1 * n))


def feasible(head: np.ndarray, tail: float, n: int, d: int, eps: float = EPS, prefixes: str = "all") -> bool:
    """Whether d choices meet the necessary condition of each prefix of the head (descending shares).

    What the h hottest keys load, with the other keys whose candidates all lie among theirs, must fit their workers.
    ``prefixes="ends"`` looks at the hottest key and the whole head alone, which bind at most skews.
    """
    if not len(head):
        return True
    upto = np.cumsum(head)
    h = np.arange(1, len(head) + 1)
    if prefixes == "ends":
        keep = np.unique([0, len(head) - 1])
        upto_h, h = upto[keep], h[keep]
    else:
        upto_h = upto
    b = n - n * ((n - 1) / n) ** (h * d)
    load = upto_h + (b / n) ** d * (upto[-1] - upto_h) + (b / n) ** 2 * tail
    return bool((load <= b * (1 / n + eps)).all())


def min_feasible_choices(head: np.ndarray, tail: float, n: int, eps: float = EPS, prefixes: str = "all") -> int:
    """The least number of choices from the hottest key's share up that is feasible; n stands for any worker.

    Feasibility need not be monotone in d, so d goes up one by one. ``prefixes="ends"`` leaves the prefixes between out altogether,
    so it may give fewer choices than they need.
    """
    head = np.asarray(head, float)
    if not len(head) or n == 1:
        return min(2, n)
    for d in range(start_choices(float(head[0]), n), n):
        if feasible(head, tail, n, d, eps, prefixes):
            return d
    return n


def single_key_ok(head: np.ndarray, tail: float, n: int, d: int, i: int, eps: float = EPS) -> bool:
    """The condition of one head key (from 0) alone."""
    b = expected_union(n, d)
    rest = float(np.sum(head)) - float(head[i])
    return bool(head[i] + (b / n) ** d * rest + (b / n) ** 2 * tail <= b * (1 / n + eps))


def replication_objective(d: int, head_size: int) -> int:
    return d * head_size


def worst_case_line(sources: int = SOURCES, eps: float = EPS) -> float:
    """Imbalance if every source errs by eps towards one worker."""
    return sources * eps


def source_memory(sources: int, n: int, capacity: int) -> int:
    """Counters that all sources hold: loads of workers and the sketches."""
    return sources * (n + capacity)


def register_sql(spark: SparkSession) -> None:
    """Temporary SQL functions of the bounds."""
    for name, args, kind, body in (
        ("default_theta", "n INT", "DOUBLE", "1D / (5 * n)"),
        ("expected_union", "n DOUBLE, throws DOUBLE", "DOUBLE", "n - n * power((n - 1) / n, throws)"),
        ("two_choice_floor", "p1 DOUBLE, n INT", "DOUBLE", "greatest(0D, p1 / 2 - 1D / n)"),
        ("two_choice_regime", "p1 DOUBLE, n INT", "STRING", "CASE WHEN p1 > 2D / n THEN 'fails' WHEN p1 <= 1D / (5 * n) THEN 'safe' ELSE 'grey' END"),
        ("memory_bound", "d BIGINT, head BIGINT, tail BIGINT", "BIGINT", "d * head + 2 * tail"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
