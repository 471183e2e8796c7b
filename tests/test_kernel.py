"""Sequential routing: hand-made traces, equivalences and invariants."""

import random
from fractions import Fraction

import numpy as np
import pytest

from skewroute.functions.hashing import md5_choice
from skewroute.operators.blocks import plan_fractions, water_fill
from skewroute.operators.kernel import Router, Scheme
from skewroute.sources.zipf import zipf_weights


def stream(m, keys, z, seed=1):
    w = zipf_weights(keys, z)
    return np.random.default_rng(seed).choice(np.arange(1, keys + 1), m, p=w / w.sum()).astype(str).tolist()


def send(scheme, keys, n, source=0):
    r = Router(scheme, n, source)
    return r, *r.run(keys, [md5_choice(k, 1, n) for k in keys], [md5_choice(k, 2, n) for k in keys])


def spread(workers, n):
    return max(np.bincount(workers, minlength=n)) / len(workers) - 1 / n


def test_trace_by_hand():
    # Candidates of a: 0, 1; of b: 1, 2; ties go to the first candidate.
    r = Router(Scheme("two_choice"), 3)
    at = {"a": (0, 1), "b": (1, 2)}
    keys = list("aabbaab")
    w, _, _ = r.run(keys, [at[k][0] for k in keys], [at[k][1] for k in keys])
    assert w == [0, 1, 2, 1, 0, 0, 2]
    r = Router(Scheme("head_round_robin", head=("a",)), 3)
    assert [r.step("a", 0, 1)[0] for _ in range(5)] == [0, 1, 2, 0, 1]
    r = Router(Scheme("any_worker", head=("a",)), 3)
    assert [r.step("a", 0, 1) for _ in range(4)] == [(0, True, 3), (1, True, 3), (2, True, 3), (0, True, 3)]
    assert r.step("b", 1, 2) == (1, False, 2)


def test_equivalences():
    keys, n = stream(3000, 50, 1), 10
    two = send(Scheme("two_choice"), keys, n)[1]
    assert send(Scheme("uniform", d=2), keys, n)[1] == two
    assert send(Scheme("uniform", d=1), keys, n)[1] == [md5_choice(k, 1, n) for k in keys]
    assert send(Scheme("any_worker", theta=Fraction(2, 1)), keys, n)[1] == two  # no key can be in the head
    assert send(Scheme("fixed_head", head=tuple(set(keys)), d=2), keys, n)[1] == two
    everywhere = send(Scheme("any_worker", head=tuple(set(keys))), keys, n)[1]
    assert max(np.bincount(everywhere)) - min(np.bincount(everywhere)) <= 1
    d = send(Scheme("fixed_head", head=("1",), d=n), keys, n)
    assert d[1] == send(Scheme("any_worker", head=("1",)), keys, n)[1]


@pytest.mark.parametrize("kind", ["two_choice", "tuned", "any_worker", "head_round_robin"])
def test_invariants(kind):
    keys, n = stream(5000, 200, 1), 10
    r, w, head, d = send(Scheme(kind), keys, n)
    assert r.load == np.bincount(w, minlength=n).tolist() and sum(r.load) == len(keys)
    for k, x, h, many in zip(keys, w, head, d, strict=True):
        if not h:
            assert x in (md5_choice(k, 1, n), md5_choice(k, 2, n)) and many == 2
        elif many < n:
            assert x in [md5_choice(k, i, n) for i in range(1, many + 1)]


def test_order_of_schemes_at_high_skew():
    keys, n = stream(20_000, 1000, 2), 50
    i = {k: spread(send(Scheme(k), keys, n)[1], n) for k in ("two_choice", "tuned", "any_worker", "head_round_robin")}
    p1 = max(np.unique(keys, return_counts=True)[1]) / len(keys)
    assert i["two_choice"] >= p1 / 2 - 1 / n
    assert i["any_worker"] <= i["tuned"] < i["two_choice"] / 10
    assert i["head_round_robin"] < i["two_choice"] / 10


def test_special_cases():
    assert send(Scheme("tuned"), ["a"] * 20, 1)[1] == [0] * 20
    assert send(Scheme("any_worker"), [], 4)[1:] == ([], [], [])
    assert set(send(Scheme("any_worker"), [None] * 40, 4)[1]) == {0, 1, 2, 3}
    r = Router(Scheme("any_worker", warmup=10), 4)
    assert not any(r.step("a", 0, 1)[1] for _ in range(10)) and r.step("a", 0, 1)[1]
    # A key with exactly the threshold's share is in the head.
    r = Router(Scheme("any_worker", theta=Fraction(1, 2)), 4)
    assert [r.step(k, 0, 1)[1] for k in "abab"] == [True, True, True, True]
    with pytest.raises(ValueError):
        Scheme("other")
    with pytest.raises(ValueError):
        Scheme("uniform")


def test_distinct_candidates_and_ties():
    r = Router(Scheme("fixed_head", d=6, head=("a",), distinct_candidates=True), 10)
    c = r.candidates("a", 6)
    assert len(c) == len(set(c)) == round(10 - 10 * 0.9**6)
    assert Router(Scheme("two_choice", tie="rotate"), 4, source=1).step("a", 0, 1)[0] == 1


def test_water_fill():
    rng = random.Random(3)
    for _ in range(50):
        load = np.array([rng.randrange(20) for _ in range(6)])
        count = rng.randrange(1, 60)
        out = water_fill(load, count)
        slow = load.copy()
        for _ in range(count):
            slow[np.argmin(slow)] += 1
        assert out.sum() == count and sorted(load + out) == sorted(slow)


def test_plan_fractions_level_the_load():
    share, weights = plan_fractions({(0, 1): 100, (1, 2): 100, (2, 2): 10}, {"a": 300}, {"a": [0, 1, 2]}, 3)
    load = np.zeros(3)
    for (a, b), n in {(0, 1): 100, (1, 2): 100, (2, 2): 10}.items():
        load[a] += n * share[a, b]
        load[b] += n * (1 - share[a, b])
    load += 300 * np.array(weights["a"])
    assert load.max() - load.mean() < 0.03 * load.sum()


@pytest.mark.parametrize("kind", ["two_choice", "tuned", "any_worker", "head_round_robin"])
@pytest.mark.parametrize("options", [{}, {"decay": 0.5, "decay_every": 300}, {"capacity": 20}])
def test_batch_loops_are_the_steps(kind, options):
    keys, n = stream(4000, 100, 1), 10
    c1, c2 = ([md5_choice(k, i, n) for k in keys] for i in (1, 2))
    slow, fast = Router(Scheme(kind, **options), n), Router(Scheme(kind, **options), n)
    want = [slow.step(k, a, b) for k, a, b in zip(keys, c1, c2, strict=True)]
    got = [fast.run(keys[i : i + 700], c1[i : i + 700], c2[i : i + 700]) for i in range(0, 4000, 700)]
    assert [x for part in got for x in zip(*part, strict=True)] == want


def test_refresh_on_every_row_agrees_where_the_head_is_stable():
    keys, n = stream(3000, 4, 1), 10
    every, seldom = send(Scheme("tuned", refresh=1), keys, n), send(Scheme("tuned", refresh=500), keys, n)
    assert spread(every[1], n) < 0.05 and spread(seldom[1], n) < 0.05
    assert all(d <= n for d in every[3])


def test_head_round_robin_can_leave_its_head_out_of_the_load():
    keys, n = stream(3000, 50, 1), 5
    r, w, head, _ = send(Scheme("head_round_robin", count_head_in_load=False), keys, n)
    assert r.load == np.bincount([x for x, h in zip(w, head, strict=True) if not h], minlength=n).tolist()
