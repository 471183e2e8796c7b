"""What the third round of findings asked for."""

import math

import duckdb

from skewroute.functions import bounds
from skewroute.plans import catalog, claims, oracles
from skewroute.sources.zipf import zipf_shares


def slow_choices(p: list[float], n: int, ranks: list[int]) -> int:
    """The least d for which the conditions of these prefixes hold."""
    tail = 1 - sum(p)
    for d in range(max(2, math.ceil(p[0] * n)), n):
        b = {h: n - n * ((n - 1) / n) ** (h * d) for h in ranks}
        if all(sum(p[:h]) + (b[h] / n) ** d * sum(p[h:]) + (b[h] / n) ** 2 * tail <= b[h] * (1 / n + bounds.EPS) for h in ranks):
            return d
    return n


def test_ends_alone_miss_a_prefix_between_them():
    p = zipf_shares(10_000, 1.4)
    head = p[p >= float(bounds.default_theta(20))]
    tail = float(1 - head.sum())
    assert bounds.min_feasible_choices(head, tail, 20) == slow_choices(head.tolist(), 20, list(range(1, len(head) + 1))) == 10
    assert bounds.min_feasible_choices(head, tail, 20, prefixes="ends") == slow_choices(head.tolist(), 20, [1, len(head)]) == 9


def test_prefixes_ablation_compares_the_ends_alone(spark, folder):
    duck = duckdb.connect()
    duck.sql(f"CREATE VIEW events AS FROM '{folder}/events.parquet'")
    shares = duck.sql(f"WITH {oracles.drawn_counts(10_000, claims._SCALES)} SELECT z, list(f / m ORDER BY f DESC), any_value(m) FROM c JOIN mm USING (z) GROUP BY z").fetchall()
    want = {}
    for n in claims.WORKERS:
        heads = [[x for x in p if round(x * m) * 5 * n >= m] for _, p, m in shares]
        want[n] = all(slow_choices(p, n, [1, len(p)]) == slow_choices(p, n, list(range(1, len(p) + 1))) for p in heads if p)
    assert {r["workers"]: r["ends_bind"] for r in catalog.QUERIES["choice_prefixes_ablation"](spark, folder).collect()} == want
    assert len(set(want.values())) == 2  # on the given tables the ends are not enough for every number of workers
