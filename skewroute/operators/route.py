"""Routing of message tables: sources, schemes, and the plan around the sequential kernel."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skewroute.functions import bounds
from skewroute.functions.hashing import hash_choice
from skewroute.operators import heavy, sketch
from skewroute.operators.kernel import Router, Scheme


def with_source(msgs: DataFrame, sources: int, order: str = "seq", dense: bool = True) -> DataFrame:
    """Deal messages over independent senders: in turn by a dense order, else by a hash of it."""
    if "source_id" in msgs.columns:
        return msgs
    base = F.col(order) if dense else F.xxhash64(order)
    return msgs.withColumn("source_id", F.pmod(base, F.lit(sources)).cast("int"))


def key_grouping(msgs: DataFrame, workers: int, family: str = "md5") -> DataFrame:
    """One hash: all messages of a key go to one worker. Wholly in the JVM."""
    return msgs.withColumn("worker", hash_choice("key", 1, workers, family)).withColumn("is_head", F.lit(False)).withColumn("n_choices", F.lit(1))


def shuffle_grouping(msgs: DataFrame, workers: int, sources: int | str = bounds.SOURCES, order: str = "seq", dense: bool = True, start: str = "zero") -> DataFrame:
    """Each source in turn over all workers, keys ignored. A source's rows are ranked in its own window."""
    if sources == "splits":  # the place of a row in its split is its turn: no window, no sort
        sourced = msgs.withColumn("source_id", F.spark_partition_id())
        turn = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    else:
        sourced = with_source(msgs, sources, order, dense)
        turn = F.row_number().over(Window.partitionBy("source_id").orderBy(order)) - 1
    first = F.col("source_id") if start == "source" else F.lit(0)
    return sourced.withColumn("worker", F.pmod(turn + first, F.lit(workers)).cast("int")).withColumn("is_head", F.lit(False)).withColumn("n_choices", F.lit(workers))


def _out(schema: T.StructType, many: bool) -> T.StructType:
    return T.StructType([*schema.fields, *([T.StructField("scheme", T.StringType())] if many else []), T.StructField("worker", T.IntegerType()), T.StructField("is_head", T.BooleanType()), T.StructField("n_choices", T.IntegerType())])


def route_many(msgs: DataFrame, schemes: list[Scheme], workers: int, sources: int | str = bounds.SOURCES, order: str = "seq", dense: bool = True, family: str = "md5", begin: dict[int, tuple[list[int], int]] | None = None) -> DataFrame:
    """All schemes over one ordered scan: the input's columns, ``source_id``, ``scheme`` and the routing of each row.

    One partition a source (more than one source a partition is fine too: state starts anew where the source
    changes). The sort by a unique order makes a retried task route as the lost one did.

    ``sources="splits"``: every input split is a source and its rows come in file order, so that nothing is exchanged or
    sorted before routing. Splits of files are the same in a retried task; other inputs need a number of sources.
    ``begin``: loads and cursor that a source starts from, ``workers + 1`` numbers a source.
    """
    sourced = msgs.withColumn("source_id", F.spark_partition_id()) if sources == "splits" else with_source(msgs, sources, order, dense)
    c = [hash_choice("key", i, workers, family).alias(f"_c{i}") for i in (1, 2)]
    dealt = sourced.select("*", *c)
    if sources != "splits":
        dealt = dealt.repartitionById(sources, F.col("source_id")).sortWithinPartitions("source_id", order)
    names, by_key = sourced.columns, any(s.kind != "two_choice" for s in schemes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, routers = None, []
        for b in batches:
            ids = b.column("source_id").to_numpy()
            cuts = [0, *(np.flatnonzero(ids[1:] != ids[:-1]) + 1).tolist(), len(ids)]
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                if lo == hi:
                    continue
                part = b.slice(lo, hi - lo)
                if ids[lo] != now:
                    now = ids[lo]
                    routers = [Router(s, workers, int(now), family) for s in schemes]
                    for r in routers if begin and int(now) in begin else ():
                        r.load, r.cursor = list(begin[int(now)][0]), begin[int(now)][1]
                keys = part.column("key").to_pylist() if by_key else [None] * (hi - lo)
                c1, c2 = (part.column(x).to_numpy().tolist() for x in ("_c1", "_c2"))
                for r in routers:
                    w, h, d = r.run(keys, c1, c2)
                    yield pa.RecordBatch.from_arrays([*(part.column(x) for x in names), pa.array([r.scheme.label] * len(w)), pa.array(w, pa.int32()), pa.array(h, pa.bool_()), pa.array(d, pa.int32())], [*names, "scheme", "worker", "is_head", "n_choices"])

    return dealt.mapInArrow(run, _out(sourced.schema, True))


def route(msgs: DataFrame, scheme: Scheme | str, workers: int, sources: int | str = bounds.SOURCES, order: str = "seq", dense: bool = True, family: str = "md5", head_scope: str = "source", load_view: str = "local") -> DataFrame:
    """Route messages by a scheme, or by ``key_grouping`` or ``shuffle_grouping``.

    ``head_scope="merged"``: one sketch of all sources is made first and its head is known to every source.
    ``load_view="global"``: one source sees all messages, in one task; for comparison on small inputs only.
    """
    if sources == "splits" and head_scope == "merged":
        raise ValueError("a merged head needs a number of sources")
    if scheme == "key_grouping":
        sourced = msgs.withColumn("source_id", F.spark_partition_id()) if sources == "splits" else with_source(msgs, sources, order, dense)
        return key_grouping(sourced, workers, family)
    if scheme == "shuffle_grouping":
        return shuffle_grouping(msgs, workers, sources, order, dense)
    scheme = Scheme(scheme) if isinstance(scheme, str) else scheme
    if load_view == "global":
        msgs, sources = msgs.withColumn("source_id", F.lit(0)), 1
    if head_scope == "merged" and scheme.head is None and scheme.kind not in ("two_choice", "uniform"):
        scheme = with_merged_head(msgs, scheme, workers, sources, order, dense)
    return route_many(msgs, [scheme], workers, sources, order, dense, family).drop("scheme")


def with_known_head(msgs: DataFrame, scheme: Scheme, workers: int) -> Scheme:
    """The scheme with the exact head of a stream, and the number of choices that this head needs."""
    theta = scheme.theta or bounds.default_theta(workers)
    head, m = heavy.head_list(msgs, theta)
    return _known(scheme, [(k, f / m) for k, f in head] if m else [], workers)


def with_merged_head(msgs: DataFrame, scheme: Scheme, workers: int, sources: int = bounds.SOURCES, order: str = "seq", dense: bool = True) -> Scheme:
    """The same from the merged sketches of the sources: at most ``capacity`` rows reach the driver."""
    theta = scheme.theta or bounds.default_theta(workers)
    capacity = scheme.capacity or sketch.default_capacity(theta)
    sourced = with_source(msgs, sources, order, dense)
    rows = sketch.merge_sketches(sketch.sketch_per_source(sourced, capacity), capacity).collect()
    t = Fraction(theta)
    return _known(scheme, [(r["key"], r["cnt"] / r["n_seen"]) for r in rows if r["cnt"] * t.denominator >= r["n_seen"] * t.numerator], workers)


def _known(scheme: Scheme, head: list[tuple], workers: int) -> Scheme:
    shares = np.array([p for _, p in head])
    d = bounds.min_feasible_choices(shares, max(0.0, 1 - float(shares.sum())), workers, scheme.eps) if scheme.kind == "tuned" else scheme.d
    return replace(scheme, head=tuple(k for k, _ in head), d=d)


def empirical_min_d(msgs: DataFrame, workers: int, theta: Fraction | None = None, tolerance: float = bounds.EPS, sources: int = bounds.SOURCES, family: str = "md5") -> tuple[int, dict[str, float]]:
    """The least d for head keys that balances as well as any worker does, and the imbalance of each: one pass."""
    from skewroute.operators.metrics import imbalance

    base = with_known_head(msgs, Scheme("any_worker", theta), workers)
    schemes = [replace(base, name="any"), *(replace(base, kind="fixed_head", d=d, name=str(d)) for d in range(2, workers + 1))]
    found = {r["scheme"]: r["imbalance"] for r in imbalance(route_many(msgs, schemes, workers, sources, family=family), workers, ["scheme"]).collect()}
    return next((d for d in range(2, workers + 1) if found[str(d)] <= found["any"] + tolerance), workers), found
