"""Mixing sources to target weights by min-cost flow over membership patterns.

Documents that belong to the same set of sources are one pattern; only patterns are seen by the flow, which sends their
tokens to the sources' quotas. A pattern's tokens can be sent several times, each time at a higher cost (convex), so
repeats are spread before they pile up. Documents are then chosen by a seeded hash: each pattern has a number of full
repeats, stretches of the hash order whose documents are taken once more, and a few exceptions that bring the total
nearer. So the choice is a comparison with a few values of the pattern, made where the document is scanned.
"""

from __future__ import annotations

import heapq
from collections import defaultdict
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skewroute.llm.common import WORD_PATTERN, materialize, read_table

WEIGHTS = (5, 2, 1)
MAX_REPEATS = 3
SEED = 20_240_601
#: Patterns that the flow takes; the table of patterns is then small enough to collect and to broadcast.
PATTERN_LIMIT = 100_000
_BITS = 12
#: Rows of one bucket of the seeded order that a task ranks; a fuller bucket is cut by further bits first.
BUCKET_ROWS = 4096


def water_fill(sizes: list[int], weights: list[float], total: float, limit: float = MAX_REPEATS) -> list[float]:
    """Shares of ``total`` by weight, none above ``limit`` times its size; the excess goes on by weight."""
    caps = [limit * s for s in sizes]
    target = [0.0] * len(sizes)
    open_, left = [i for i in range(len(sizes)) if weights[i] > 0], float(total)
    while open_:
        unit = left / sum(weights[i] for i in open_)
        over = [i for i in open_ if unit * weights[i] > caps[i]]
        for i in over or open_:
            target[i] = float(caps[i]) if over else unit * weights[i]
        if not over:
            break
        left -= sum(caps[i] for i in over)
        open_ = [i for i in open_ if i not in set(over)]
    return target


class Network:
    """Supply, patterns, sources and sink of one component; arcs in pairs, an arc and its reverse."""

    def __init__(self, patterns: dict[tuple[int, ...], int], quotas: dict[int, int], repeats: int):
        self.arcs: list[list[int]] = []  # [to, room, cost]
        source_at = {s: 1 + len(patterns) + k for k, s in enumerate(sorted(quotas))}
        self.sink = 1 + len(patterns) + len(quotas)
        self.out: list[list[int]] = [[] for _ in range(self.sink + 1)]
        self.carry = {}
        for k, (p, size) in enumerate(patterns.items()):
            for r in range(repeats):  # the r-th repeat of a pattern's tokens costs r a token
                self._arc(0, 1 + k, size, r)
            for s in p:
                self.carry[p, s] = self._arc(1 + k, source_at[s], repeats * size, 0)
        for s, quota in quotas.items():
            self._arc(source_at[s], self.sink, quota, 0)

    def _arc(self, a: int, b: int, room: int, cost: int) -> int:
        self.out[a].append(len(self.arcs))
        self.arcs.append([b, room, cost])
        self.out[b].append(len(self.arcs))
        self.arcs.append([a, 0, -cost])
        return len(self.arcs) - 2

    def _prices(self, price: list[int]) -> bool:
        """Lift the prices by the distances from the supply; whether the sink can still be reached."""
        arcs, out, far, heap = self.arcs, self.out, {0: 0}, [(0, 0)]
        while heap:
            d, a = heapq.heappop(heap)
            if d > far[a]:
                continue
            for e in out[a]:
                b, room, cost = arcs[e]
                if room and (n := d + cost + price[a] - price[b]) < far.get(b, n + 1):
                    far[b] = n
                    heapq.heappush(heap, (n, b))
        most = max(far.values())
        for i in range(len(price)):
            price[i] += far.get(i, most)
        return self.sink in far

    def _levels(self, price: list[int]) -> list[int]:
        level, todo = [-1] * len(price), [0]
        level[0] = 0
        for a in todo:
            for e in self.out[a]:
                b, room, cost = self.arcs[e]
                if room and level[b] < 0 and cost + price[a] == price[b]:
                    level[b] = level[a] + 1
                    todo.append(b)
        return level

    def _push(self, price: list[int], level: list[int]) -> None:
        """A blocking flow over arcs without reduced cost that go one level up."""
        arcs, out, sink, turn, path, a = self.arcs, self.out, self.sink, [0] * len(price), [], 0
        while True:
            if a == sink:
                flow = min(arcs[e][1] for e in path)
                for e in path:
                    arcs[e][1] -= flow
                    arcs[e ^ 1][1] += flow
                path, a = [], 0
            while turn[a] < len(out[a]):
                e = out[a][turn[a]]
                b, room, cost = arcs[e]
                if room and level[b] == level[a] + 1 and cost + price[a] == price[b]:
                    path.append(e)
                    a = b
                    break
                turn[a] += 1
            else:
                if not path:
                    return
                a = arcs[path.pop() ^ 1][0]
                turn[a] += 1

    def solve(self) -> dict[tuple[tuple[int, ...], int], int]:
        """Maximum flow of least cost, by phases of equal path cost; there are few, as repeats are."""
        price = [0] * (self.sink + 1)
        while self._prices(price):
            while (level := self._levels(price))[self.sink] >= 0:
                self._push(price, level)
        return {key: self.arcs[e ^ 1][1] for key, e in self.carry.items() if self.arcs[e ^ 1][1]}


def components(patterns: dict[tuple[int, ...], int]) -> list[dict[tuple[int, ...], int]]:
    """Patterns that sources tie together; what one takes is nothing to another."""
    root: dict[int, int] = {}

    def find(s: int) -> int:
        while root.setdefault(s, s) != s:
            root[s] = s = root[root[s]]
        return s

    for p in patterns:
        for s in p:
            root[find(s)] = find(p[0])
    out: dict[int, dict] = defaultdict(dict)
    for p, size in patterns.items():
        if p:
            out[find(p[0])][p] = size
    return list(out.values())


def route(patterns: dict[tuple[int, ...], int], quotas: list[int], repeats: int = MAX_REPEATS) -> dict[tuple[tuple[int, ...], int], int]:
    """Tokens that each pattern sends to each of its sources: a maximum flow of least cost, one network a component."""
    sent: dict[tuple[tuple[int, ...], int], int] = {}
    for part in components(patterns):
        sent |= Network(part, {s: quotas[s] for p in part for s in p}, repeats).solve()
    return sent


def word_count(text: Column) -> Column:
    """Words of a text: each becomes one letter, and what is between them goes; no list of words is ever built."""
    return F.coalesce(F.length(F.translate(F.regexp_replace(text, WORD_PATTERN, "x"), " \t\n\x0b\x0c\r", "")), F.lit(0)).cast("long")


def seeded(doc_id: Column, text: Column, seed: int) -> Column:
    return F.xxhash64(F.lit(seed), doc_id.cast("long"), F.length(text))


@dataclass
class MixPlan:
    """What decides a row, per pattern, as a small table: full repeats, stretches of the seeded order, exceptions; and the size of the network."""

    table: DataFrame
    sources: list[str | None]
    targets: list[float]
    sent: dict[tuple[tuple[int, ...], int], int]
    arcs: int = 0


def _order(h: str = "h", i: str = "i") -> Column:
    return F.struct(F.col(h), F.col(i))


def plan(rows: DataFrame, weights: tuple[float, ...] = WEIGHTS, repeats: int = MAX_REPEATS, total: int | None = None) -> MixPlan:
    """Plan a mix of materialised ``rows(sources array<string>, size, h, i)``; ``h`` is the seeded order, ``i`` the id.

    The driver takes the patterns, at most ``PATTERN_LIMIT``, with their sizes, and a few places in the seeded order
    of each. ``total`` is the size of the mix (None: that of all rows, each once).
    """
    spark = rows.sparkSession
    found = rows.groupBy("sources").agg(F.sum("size").alias("size")).limit(PATTERN_LIMIT + 1).collect()
    if len(found) > PATTERN_LIMIT:
        raise ValueError(f"more than {PATTERN_LIMIT} membership patterns")
    names = sorted({s for r in found for s in r["sources"]}, key=lambda s: (s is None, s or ""))
    at = {s: k for k, s in enumerate(names)}
    key = {tuple(r["sources"]): tuple(sorted({at[s] for s in r["sources"]})) for r in found}
    patterns: dict[tuple[int, ...], int] = defaultdict(int)
    for r in found:
        patterns[key[tuple(r["sources"])]] += r["size"]
    within = [sum(size for p, size in patterns.items() if k in p) for k in range(len(names))]
    ratio = [float(weights[k % len(weights)]) for k in range(len(names))]
    targets = water_fill(within, ratio, sum(patterns.values()) if total is None else total, repeats)
    sent = route(patterns, [round(t) for t in targets], repeats)
    wanted: dict[tuple[int, ...], int] = defaultdict(int)
    for (p, _), n in sent.items():
        wanted[p] += n
    number = {p: k for k, p in enumerate(patterns)}
    whole = {p: wanted[p] // size if size else 0 for p, size in patterns.items()}
    extra = {p: wanted[p] - whole[p] * size for p, size in patterns.items()}

    schema = T.StructType([T.StructField("sources", T.ArrayType(T.StringType())), T.StructField("pattern", T.LongType())])
    table = spark.createDataFrame([(list(s), number[p]) for s, p in key.items()], schema)
    cuts, toggles = _cuts(rows.join(F.broadcast(table), "sources").select("pattern", "size", "h", "i"), {number[p]: n for p, n in extra.items()})
    final = T.StructType([T.StructField("sources", T.ArrayType(T.StringType())), T.StructField("whole", T.LongType()), T.StructField("cuts", T.ArrayType(_CUT)), T.StructField("toggles", T.ArrayType(_ROW)), T.StructField("target", T.DoubleType()), T.StructField("source_size", T.LongType())])
    out = []
    for s, p in key.items():
        alone, k = len(p) == 1, number[p]
        out.append((list(s), whole[p], cuts[k], toggles[k], targets[p[0]] if alone else None, within[p[0]] if alone else None))
    arcs = sum(repeats + len(p) for p in patterns if p) + len(names)
    return MixPlan(spark.createDataFrame(out, final), names, targets, sent, arcs)


_LOW, _HIGH = -(1 << 63), (1 << 63) - 1
_CUT = T.StructType([T.StructField(c, T.LongType()) for c in ("limit", "low_h", "low_i", "h", "i")])
_ROW = T.StructType([T.StructField(c, T.LongType()) for c in ("h", "i")])


def _taken(cuts: Column, size: Column) -> Column:
    """Whether one of the cuts takes a row: in its stretch of the seeded order, and no larger than its limit."""
    at = _order()
    return F.exists(cuts, lambda c: (size <= c["limit"]) & (at > F.struct(c["low_h"].alias("h"), c["low_i"].alias("i"))) & (at <= F.struct(c["h"].alias("h"), c["i"].alias("i"))))


def _picked(cuts: Column, toggles: Column, size: Column) -> Column:
    at = _order()
    return _taken(cuts, size) != F.exists(toggles, lambda x: at == F.struct(x["h"].alias("h"), x["i"].alias("i")))


def _cuts(known: DataFrame, extra: dict[int, int], rounds: int = 4) -> tuple[dict[int, list[tuple]], dict[int, list[tuple[int, int]]]]:
    """Which rows of each pattern make up ``extra`` tokens: stretches of the seeded order, and rows that mend the rest.

    A stretch takes rows in order while they fit; the row that does not fit is left out, and the next stretch goes
    on behind it with rows that fit what is left. Sums run over buckets of the order's leading bits; the one in which the tokens run out is
    cut by more bits until it holds ``BUCKET_ROWS`` places at most, and only then ranked. Rows at one place go together.
    After ``rounds`` stretches a pattern may still lack less than its least row left behind; ``_toggles`` goes on from there.
    """
    spark = known.sparkSession
    cuts: dict[int, list[tuple]] = {p: [] for p in extra}
    gap, low = dict(extra), {p: (_LOW, _LOW) for p in extra}
    for _ in range(rounds):
        todo = [(p, gap[p], *low[p]) for p in extra if gap[p] > 0 and low[p] != (_HIGH, _HIGH)]
        if not todo:
            break
        marks = spark.createDataFrame(todo, "pattern long, gap long, low_h long, low_i long")
        fits = known.join(F.broadcast(marks), "pattern").where((F.col("size") <= F.col("gap")) & (_order() > _order("low_h", "low_i"))).select("pattern", "gap", "size", "h", "i", F.lit(0).cast("long").alias("before"))
        edge: dict[int, tuple[int, int, int]] = {}  # pattern: bits, bucket, tokens before it
        totals, bits, rows = {}, 0, fits
        while True:
            bits += _BITS
            bucket = F.shiftrightunsigned(F.col("h").bitwiseXOR(F.lit(_LOW)), 64 - bits)  # ascending as signed h
            sums = rows.groupBy("pattern", "gap", "before", bucket.alias("b")).agg(F.sum("size").alias("n"), F.count("*").alias("c"))
            upto = sums.selectExpr("*", "before + sum(n) OVER (PARTITION BY pattern ORDER BY b) AS upto").groupBy("pattern").agg(F.min(F.when(F.col("upto") > F.col("gap"), F.struct("b", (F.col("upto") - F.col("n")).alias("before"), "c"))).alias("edge"), F.max("upto").alias("all"))
            found = {r["pattern"]: (r["edge"], r["all"]) for r in upto.collect()}
            totals = totals or {p: total for p, (_, total) in found.items()}
            split = [(p, e["b"], e["before"]) for p, (e, _) in found.items() if e is not None]
            edge |= {p: (bits, b, before) for p, b, before in split}
            if not split:
                break
            inside = F.broadcast(spark.createDataFrame(split, "pattern long, eb long, eb_before long"))
            rows = fits.join(inside, "pattern").where(bucket == F.col("eb")).select("pattern", "gap", "size", "h", "i", F.col("eb_before").alias("before"))
            if bits >= 60 or max(e["c"] for e, _ in found.values() if e is not None) <= BUCKET_ROWS:
                break
        last: dict[int, tuple] = {}
        if edge:
            places = rows.groupBy("pattern", "gap", "before", "h", "i").agg(F.sum("size").alias("n"))
            ranked = places.selectExpr("pattern", "h", "i", "gap", "before + sum(n) OVER (PARTITION BY pattern ORDER BY h, i) AS upto").where("upto <= gap")
            last = {r["pattern"]: tuple(r["x"]) for r in ranked.groupBy("pattern").agg(F.max(F.struct("h", "i", "upto")).alias("x")).collect()}
        for p, room, *start in todo:
            if p not in edge:  # all that fit are taken
                stop, used = (_HIGH, _HIGH), totals.get(p, 0)
            elif p in last:
                *stop, used = last[p]
            else:
                width, b, used = edge[p]
                stop = (max((b << 64 - width) + _LOW - 1, _LOW), _HIGH)
            cuts[p].append((room, *start, *stop))
            gap[p], low[p] = room - used, tuple(stop)
    return cuts, _toggles(known, gap, cuts, extra)


def _toggles(known: DataFrame, gap: dict[int, int], cuts: dict[int, list[tuple]], extra: dict[int, int], steps: int = 8) -> dict[int, list[tuple[int, int]]]:
    """Rows to take or leave against the cuts, one a step, as long as each brings a pattern's total nearer."""
    spark, gap = known.sparkSession, dict(gap)
    out: dict[int, list[tuple[int, int]]] = {p: [] for p in extra}
    todo = {p for p in extra if gap[p] > 0}
    kind = T.StructType([T.StructField("pattern", T.LongType()), T.StructField("gap", T.LongType()), T.StructField("cuts", T.ArrayType(_CUT)), T.StructField("toggles", T.ArrayType(_ROW))])
    for _ in range(steps):
        if not todo:
            break
        marks = spark.createDataFrame([(p, gap[p], cuts[p], out[p]) for p in sorted(todo)], kind)
        on = _picked(F.col("cuts"), F.col("toggles"), F.col("size"))
        change = F.when(on, -F.col("size")).otherwise(F.col("size"))
        off = F.abs(F.col("gap") - change)
        near = known.join(F.broadcast(marks), "pattern").where((F.col("size") > 0) & (off < F.abs("gap")))
        best = {r["pattern"]: r["x"] for r in near.groupBy("pattern").agg(F.min(F.struct(off.alias("off"), "h", "i", change.alias("change"))).alias("x")).collect()}
        todo = set()
        for p, x in best.items():
            out[p].append((x["h"], x["i"]))
            gap[p] -= x["change"]
            if gap[p]:
                todo.add(p)
    return out


def choose(rows: DataFrame, mix: MixPlan) -> DataFrame:
    """Add ``repeats`` (how often the mix takes the row), ``target`` and ``source_size`` to ``rows(sources, size, h, i, ...)``."""
    picked = _picked(F.col("cuts"), F.col("toggles"), F.col("size")).cast("long")
    return rows.join(F.broadcast(mix.table), "sources").withColumn("repeats", F.col("whole") + picked).drop("whole", "cuts", "toggles")


def _rows(docs: DataFrame, seed: int) -> list[Column]:
    return [F.array("source").alias("sources"), word_count(F.col("text")).alias("size"), seeded(F.col("doc_id"), F.col("text"), seed).alias("h"), F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("i")]


def mix_documents(docs: DataFrame, seed: int = SEED) -> DataFrame:
    """``(doc_id, size, source_size, target, taken)`` of every row of ``docs(doc_id, source, text)``.

    A null source is a source of its own, the last one. Null and empty texts have size 0 and are never taken. Rows
    that repeat a document are documents of their own, chosen alike. An empty table gives an empty table.
    """
    rows = materialize(docs.select("doc_id", *_rows(docs, seed)), "sizes")
    chosen = choose(rows, plan(rows))
    return chosen.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("repeats")).alias("taken"))


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_documents(read_table(spark, sf_dir, "documents"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it; the choice is made where the document is scanned."""
    names = docs.columns
    mix = plan(materialize(docs.select(*_rows(docs, SEED)), "sizes"))
    keyed = docs.select(F.struct(*names).alias("_d"), *_rows(docs, SEED))
    copies = choose(keyed, mix).where("size > 0 AND repeats > 0").withColumn("_n", F.explode(F.sequence(F.lit(1), F.col("repeats").cast("int"))))
    return copies.select("_d.*")
