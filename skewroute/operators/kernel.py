"""The sequential heart of routing: one sender's view, message by message.

A router sees only what its own source has sent. It is plain Python over dense lists, since each choice depends on all
before it; everything that does not depend on order (hashes of all keys, placement, measures) stays outside, in the JVM.
Several routers can share one scan, so a comparison of schemes or a sweep of a parameter is one pass.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from fractions import Fraction

import numpy as np

from skewroute.functions import bounds
from skewroute.functions.hashing import CHOICES
from skewroute.operators.sketch import CounterSketch, default_capacity


#: Keys whose further choices a router remembers; hashing one again costs time, nothing else.
MEMO_KEYS = 1 << 16


@dataclass(frozen=True)
class Scheme:
    """A routing scheme and its options.

    kind: ``two_choice`` (all keys the least loaded of two), ``uniform`` (of d for all keys), ``tuned`` (head keys of
    a computed d), ``any_worker`` (head keys any worker), ``head_round_robin`` (head keys in turn), ``fixed_head``
    (head keys of a given d). ``head``: a known head as keys, hottest first; None: learnt from the stream by a
    sketch. ``d``: given choices; for ``tuned`` with a known head, computed beforehand. ``refresh``: head rows after
    which d is computed again at the latest (1: on every head row). ``tie``: ``first`` candidate or ``rotate`` by
    source. ``warmup``: rows of a source before any key counts as head. ``decay``: factor on all sketch counts after every
    ``decay_every`` rows, so that the head follows drift.
    """

    kind: str
    theta: Fraction | None = None
    eps: float = bounds.EPS
    d: int | None = None
    head: tuple | None = None
    capacity: int | None = None
    refresh: int = 1000
    tie: str = "first"
    warmup: int = 0
    count_head_in_load: bool = True
    guaranteed: bool = False
    distinct_candidates: bool = False
    decay: float | None = None
    decay_every: int = 1000
    name: str = ""

    KINDS = ("two_choice", "uniform", "tuned", "any_worker", "head_round_robin", "fixed_head")

    def __post_init__(self):
        if self.kind not in self.KINDS:
            raise ValueError(f"unknown scheme {self.kind}")
        if self.kind in ("uniform", "fixed_head") and not self.d:
            raise ValueError(f"{self.kind} needs d")
        if self.tie not in ("first", "rotate"):
            raise ValueError(f"unknown tie rule {self.tie}")

    @property
    def label(self) -> str:
        return self.name or self.kind


class Router:
    """State of one source under one scheme."""

    def __init__(self, scheme: Scheme, n: int, source: int = 0, family: str = "md5"):
        self.scheme, self.n, self.source = scheme, n, source
        self.load = [0] * n
        self.cursor = 0
        self.choice: Callable = CHOICES[family]
        self.memo: dict = {}
        theta = scheme.theta or bounds.default_theta(n)
        self.num, self.den = theta.numerator, theta.denominator
        self.d = scheme.d or 2
        self.online = scheme.kind not in ("two_choice", "uniform") and scheme.head is None
        self.known = frozenset(scheme.head) if scheme.head is not None else frozenset()
        self.sketch = CounterSketch(scheme.capacity or default_capacity(theta), scheme.decay, scheme.decay_every) if self.online else None
        self.hot: set = set()
        self.age = 0
        self.history: list[tuple[int, int]] = []  # (messages seen, d) at each change

    def state(self) -> dict:
        """All that has to outlive the process, in plain containers."""
        s = self.sketch
        held = None if s is None else (s.counts, s.errors, s.total, s._buckets, s._low, s._since)
        return {"load": self.load, "cursor": self.cursor, "d": self.d, "hot": self.hot, "age": self.age, "history": self.history, "sketch": held}

    def restore(self, state: dict) -> Router:
        self.load, self.cursor, self.d, self.hot, self.age, self.history = (state[k] for k in ("load", "cursor", "d", "hot", "age", "history"))
        if self.sketch is not None:
            s = self.sketch
            s.counts, s.errors, s.total, s._buckets, s._low, s._since = state["sketch"]
        return self

    def candidates(self, key, d: int, first: tuple[int, int] | None = None) -> list[int]:
        """The first d choices of a key; computed once and extended. Collisions are kept unless distinct ones are asked."""
        have = self.memo.get(key)
        if have is None:
            if len(self.memo) >= MEMO_KEYS:
                self.memo.clear()  # a sender holds nothing that grows with the keys it has seen
            have = self.memo[key] = list(first) if first is not None else []
        if self.scheme.distinct_candidates:
            want = min(self.n, round(bounds.expected_union(self.n, d)))
            seen, out, i = set(), [], 0
            while len(out) < want and i < 50 * self.n:
                if i == len(have):
                    have.append(self.choice(key, i + 1, self.n))
                if have[i] not in seen:
                    seen.add(have[i])
                    out.append(have[i])
                i += 1
            return out
        while len(have) < d:
            have.append(self.choice(key, len(have) + 1, self.n))
        return have[:d]

    def is_head(self, key) -> bool:
        """Count a key and tell whether it is in the head, the present message included."""
        if not self.online:
            return key in self.known
        s = self.sketch
        count = s.add(key)
        if self.scheme.guaranteed:
            count -= s.errors.get(key, 0)
        return s.total > self.scheme.warmup and count * self.den >= self.num * s.total

    def _refresh(self, key) -> None:
        """The number of choices for the head as it stands. Keys leave it silently as the stream goes on."""
        self.age += 1
        if key in self.hot and self.age < self.scheme.refresh:
            return
        self.age = 0
        s = self.sketch
        self.hot.add(key)
        self.hot = {k for k in self.hot if s.counts.get(k, 0) * self.den >= self.num * s.total}
        shares = np.array(sorted((s.counts[k] for k in self.hot), reverse=True), float) / s.total
        d = bounds.min_feasible_choices(shares, max(0.0, 1.0 - float(shares.sum())), self.n, self.scheme.eps)
        if d != self.d:
            self.history.append((s.total, d))
            self.d = d

    def _least(self, workers) -> int:
        load = self.load
        if self.scheme.tie == "rotate":
            k = self.source % len(workers)
            workers = [*workers[k:], *workers[:k]]
        best = workers[0]
        low = load[best]
        for w in workers:
            if load[w] < low:
                low, best = load[w], w
        return best

    def _head_step(self, key, c1: int, c2: int) -> tuple[int, int]:
        """Worker and number of choices of a message whose key is in the head."""
        kind, n = self.scheme.kind, self.n
        if kind == "head_round_robin":
            w = self.cursor
            self.cursor = (w + 1) % n
            if self.scheme.count_head_in_load:
                self.load[w] += 1
            return w, n
        d = n
        if kind != "any_worker":
            if kind == "tuned" and self.online:
                self._refresh(key)
            # More hashes than workers may be given to a fixed head: it then reaches workers by hashing alone.
            d = self.d if kind == "fixed_head" and self.d > n else min(self.d, n)
        if d != n:
            w = self._least(self.candidates(key, d, (c1, c2)))
        else:
            w = self.load.index(min(self.load)) if self.scheme.tie == "first" else self._least(range(n))
        self.load[w] += 1
        return w, d

    def step(self, key, c1: int, c2: int) -> tuple[int, bool, int]:
        """Route one message: worker, whether its key was in the head, and its number of choices."""
        kind = self.scheme.kind
        if kind == "uniform":
            d = self.scheme.d
            w = c1 if d == 1 else self._least((c1, c2) if d == 2 else self.candidates(key, d, (c1, c2)))
        elif kind != "two_choice" and self.is_head(key):
            w, d = self._head_step(key, c1, c2)
            return w, True, d
        else:
            w, d = self._least((c1, c2)), 2
        self.load[w] += 1
        return w, False, d

    def run(self, keys: list, c1: list[int], c2: list[int]) -> tuple[list[int], list[bool], list[int]]:
        """Route a batch in order. The commonest steps (two choices, tail keys beside a learnt head) have loops of their own."""
        plain = self.scheme.tie == "first" and self.scheme.kind != "uniform"
        if plain and self.scheme.kind == "two_choice":
            load, out = self.load, []
            for a, b in zip(c1, c2, strict=True):
                w = b if load[b] < load[a] else a
                load[w] += 1
                out.append(w)
            return out, [False] * len(out), [2] * len(out)
        if plain and self.online and not self.scheme.guaranteed and not self.scheme.warmup:
            return self._run_online(keys, c1, c2)
        step = self.step
        rows = [step(k, a, b) for k, a, b in zip(keys, c1, c2, strict=True)]
        return [r[0] for r in rows], [r[1] for r in rows], [r[2] for r in rows]

    def _run_online(self, keys: list, c1: list[int], c2: list[int]) -> tuple[list[int], list[bool], list[int]]:
        s, load, num, den, head_step = self.sketch, self.load, self.num, self.den, self._head_step
        add, workers, heads, choices = s.add, [], [], []
        for k, a, b in zip(keys, c1, c2, strict=True):
            if add(k) * den >= num * s.total:
                w, d = head_step(k, a, b)
                heads.append(True)
            else:
                w, d = (b if load[b] < load[a] else a), 2
                load[w] += 1
                heads.append(False)
            workers.append(w)
            choices.append(d)
        return workers, heads, choices


class Fleet:
    """Routers of one source at several points of a grid, of which only loads are wanted.

    What is hot does not depend on where messages go, so schemes that learn the same head share one sketch, and each then runs over the marked rows.
    Loads are those of routers that run alone.
    """

    def __init__(self, points: list[tuple[int, Scheme]], source: int = 0):
        self.routers = [Router(s, n, source) for n, s in points]
        self.heads = [[0] * r.n for r in self.routers]
        self.low = [(0, 0)] * len(self.routers)  # of loads: the least, and a place before which none is as low
        self.cache: list[tuple[int, dict]] = [(0, {})] * len(self.routers)
        self.shared: dict[tuple, list[int]] = {}
        self.two, self.alone = [], []
        for i, r in enumerate(self.routers):
            s = r.scheme
            if s.kind == "two_choice" and s.tie == "first":
                self.two.append(i)
            elif s.kind not in ("two_choice", "uniform") and s.tie == "first" and s.count_head_in_load and not s.guaranteed and not s.warmup and (r.online or s.decay is None):
                key = (r.n, r.num, r.den, s.capacity, s.decay, s.decay_every) if r.online else (r.n, r.known)
                self.shared.setdefault(key, []).append(i)
                r.sketch = self.routers[self.shared[key][0]].sketch
                if r.online:
                    r.sketch.keep_errors = False
            else:
                self.alone.append(i)

    def run(self, keys: list, h1: np.ndarray, h2: np.ndarray) -> None:
        """Route messages in order; ``h1`` and ``h2`` are whole hashes, of which each number of workers takes its remainder."""
        choices = {n: ((h1 % n).tolist(), (h2 % n).tolist()) for n in {r.n for r in self.routers}}
        for i in self.two:
            r = self.routers[i]
            load = r.load
            for a, b in zip(*choices[r.n], strict=True):
                if load[b] < load[a]:
                    load[b] += 1
                else:
                    load[a] += 1
        for members in self.shared.values():
            hot, many = self._mark(members, keys)
            for i in members:
                self._route(i, keys, *choices[self.routers[i].n], hot, many.get(i))
        for i in self.alone:
            r, head = self.routers[i], self.heads[i]
            w, h, _ = r.run(keys, *choices[r.n])
            for x, is_head in zip(w, h, strict=True):
                if is_head:
                    head[x] += 1

    def _mark(self, members: list[int], keys: list) -> tuple[bytearray, dict[int, list[int]]]:
        """Which rows are hot, and for each tuned scheme the number of choices at each hot row."""
        first = self.routers[members[0]]
        hot = bytearray(len(keys))
        if not first.online:
            known = first.known
            for i, k in enumerate(keys):
                if k in known:
                    hot[i] = 1
            return hot, {}
        tuned = [(self.routers[i], []) for i in members if self.routers[i].scheme.kind == "tuned"]
        for i in first.sketch.hot_rows(keys, first.num, first.den):
            hot[i] = 1
            for r, out in tuned:
                r._refresh(keys[i])
                out.append(r.d)
        return hot, {i: out for i, (_, out) in zip((i for i in members if self.routers[i].scheme.kind == "tuned"), tuned, strict=True)}

    def _route(self, i: int, keys: list, c1: list[int], c2: list[int], hot: bytearray, many: list[int] | None) -> None:
        r, head = self.routers[i], self.heads[i]
        load, n, kind = r.load, r.n, r.scheme.kind
        if kind == "head_round_robin":
            w = r.cursor
            for a, b, h in zip(c1, c2, hot, strict=True):
                if h:
                    load[w] += 1
                    head[w] += 1
                    w = w + 1 if w + 1 < n else 0
                elif load[b] < load[a]:
                    load[b] += 1
                else:
                    load[a] += 1
            r.cursor = w
            return
        low, at = self.low[i]
        given = iter(many) if many is not None else None
        d = n if kind == "any_worker" else r.d if kind == "fixed_head" and r.d > n else min(r.d, n)
        of, cache = self.cache[i]
        for k, a, b, h in zip(keys, c1, c2, hot, strict=True):
            if not h:
                if load[b] < load[a]:
                    load[b] += 1
                else:
                    load[a] += 1
                continue
            if given is not None:
                d = min(next(given), n)
            if d == n:
                try:
                    w = at = load.index(low, at)
                except ValueError:
                    low = min(load)
                    w = at = load.index(low)
            else:
                if d != of or len(cache) >= MEMO_KEYS:
                    of, cache = d, {}
                cand = cache.get(k)
                if cand is None:
                    cand = cache[k] = tuple(dict.fromkeys(r.candidates(k, d, (a, b))))  # of workers that come twice the first place counts
                w = min(cand, key=load.__getitem__) if len(cand) > 6 else r._least(cand)
            load[w] += 1
            head[w] += 1
        self.low[i], self.cache[i] = (low, at), (of, cache)
