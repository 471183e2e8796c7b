"""Counter sketches against exact counts; the number of choices against golden values and simulation."""

from collections import Counter
from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from skewroute.functions import bounds
from skewroute.operators.heavy import head_size
from skewroute.operators.metrics import memory_bound
from skewroute.operators.sketch import CounterSketch, default_capacity
from skewroute.sources.zipf import zipf_shares, zipf_weights


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 30), max_size=300), st.lists(st.integers(0, 30), max_size=100), st.integers(1, 12))
def test_bounds_hold_and_survive_merging(a, b, capacity):
    def sketch(xs):
        s = CounterSketch(capacity)
        for x in xs:
            s.add(x)
        return s

    for s, xs in ((sketch(a), a), (sketch(b), b), (sketch(a).merge(sketch(b)), a + b), (sketch(b).merge(sketch(a)), a + b)):
        true = Counter(xs)
        assert s.total == len(xs) and len(s.counts) <= capacity
        for k, c, e in s.items():
            assert c - e <= true[k] <= c
        assert s.floor() <= len(xs) / capacity
        for k, n in true.items():
            if n > s.total / capacity and s is not None and (xs is a or xs is b):
                assert k in s.counts
    if a:
        assert sum(sketch(a).counts.values()) == len(a)


def test_eviction_takes_the_oldest_least_counter():
    s = CounterSketch(2)
    for k in "aabc":
        s.add(k)
    assert s.items() == [("a", 2, 0), ("c", 2, 1)]
    assert s.add("b") == 3 and s.items() == [("b", 3, 2), ("c", 2, 1)]
    s.add("b", 5)
    assert s.heavy(Fraction(1, 2)) == [("b", 8, 2)]


def test_decay_forgets():
    s = CounterSketch(10, decay=0.5, decay_every=100)
    for k in ["old"] * 400 + ["new"] * 400:
        s.add(k)
    assert s.counts["new"] > s.counts.get("old", 0) * 5


def test_capacity_rule():
    assert default_capacity(Fraction(1, 100)) == 400


#: (head size, start, d) for exact Zipf shares of 10,000 keys at the default threshold; n stands for any worker.
GOLDEN = {(5, 1.0): (2, 2, 2), (5, 1.4): (4, 2, 5), (10, 1.2): (7, 3, 3), (10, 1.4): (7, 4, 8), (20, 1.6): (10, 9, 13), (50, 0.8): (16, 2, 2), (50, 1.4): (23, 17, 22), (50, 2.0): (12, 31, 49), (80, 1.8): (19, 43, 63), (100, 1.0): (51, 11, 12), (100, 2.0): (17, 61, 95)}


@pytest.mark.parametrize(("n", "z"), GOLDEN)
def test_choices_of_zipf(n, z):
    p = zipf_shares(10_000, z)
    size = head_size(p, bounds.default_theta(n))
    head, tail = p[:size], float(1 - p[:size].sum())
    d = bounds.min_feasible_choices(head, tail, n)
    assert (size, bounds.start_choices(float(p[0]), n), d) == GOLDEN[n, z]
    assert size <= 5 * n
    assert bounds.min_feasible_choices(head, tail, n, prefixes="ends") == d
    if d < n:
        assert bounds.feasible(head, tail, n, d) and all(bounds.single_key_ok(head, tail, n, d, i) for i in range(1))
        assert d == bounds.start_choices(float(p[0]), n) or not bounds.feasible(head, tail, n, d - 1)


def test_expected_union():
    assert bounds.expected_union(2, 2) == 1.5 and abs(bounds.expected_union(10, 1) - 1) < 1e-12
    draws = np.random.default_rng(0).integers(0, 20, (4000, 30))
    assert abs(np.mean([len(set(r)) for r in draws.tolist()]) - bounds.expected_union(20, 30)) < 0.1


def test_no_head():
    assert bounds.min_feasible_choices(np.array([]), 1.0, 20) == 2


def test_memory_bounds_are_ordered():
    args = (10_000, 50, 100)
    order = [memory_bound(s, *args, 20) for s in ("key_grouping", "two_choice", "tuned", "any_worker", "shuffle_grouping")]
    assert order == sorted(order) and memory_bound("any_worker", *args) == memory_bound("head_round_robin", *args)


def test_weights_stay_in_range():
    for keys, z in ((20_000, 1), (100_000, 0.5), (1000, 2.0), (10, 0)):
        w = zipf_weights(keys, z)
        assert 0 < w.sum() < 2**31 and (np.diff(w) <= 0).all()
    assert abs(zipf_shares(10_000, 2)[0] - 0.608) < 1e-3
