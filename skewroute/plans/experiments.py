"""The experiments: grids over schemes, workers, thresholds, skews and streams, each stream and scale one pass."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from fractions import Fraction
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skewroute.functions import bounds
from skewroute.operators import metrics, queueing
from skewroute.operators.kernel import Scheme
from skewroute.operators.route import key_grouping, route_many, shuffle_grouping, with_known_head, with_source
from skewroute.plans import grids
from skewroute.sources import tables, zipf


@dataclass
class ExperimentGrid:
    """Default parameters of the simulations."""

    workers: list[int] = field(default_factory=lambda: [5, 10, 20, 50, 100])
    sources: int = bounds.SOURCES
    eps: float = bounds.EPS
    z: list[float] = field(default_factory=lambda: [round(0.1 * i, 1) for i in range(1, 21)])
    keys: list[int] = field(default_factory=lambda: [10**4, 10**5, 10**6])
    messages: int = 10**7


COMPARED = ("two_choice", "tuned", "any_worker", "head_round_robin")
#: The cluster run: senders, workers, skews, keys, messages, service time.
CLUSTER = {"sources": 48, "workers": 80, "z": (1.4, 1.7, 2.0), "keys": 10**4, "messages": 2 * 10**6, "service_us": 1000}


def compare(msgs: DataFrame, n: int, schemes=COMPARED, sources: int = bounds.SOURCES, dense: bool = True, theta: Fraction | None = None, known: bool = False) -> DataFrame:
    """Rows of all sequential schemes over one scan, with ``scheme``."""
    made = [Scheme(k, theta) for k in schemes]
    made = [with_known_head(msgs, s, n) if known and s.kind != "two_choice" else s for s in made]
    return route_many(msgs, made, n, sources, dense=dense)


def with_baselines(msgs: DataFrame, n: int, sources: int = bounds.SOURCES, dense: bool = True, **options) -> DataFrame:
    """``(scheme, seq, key, source_id, worker, is_head, n_choices)`` of the sequential schemes and of both groupings."""
    names = ["scheme", "seq", "key", "source_id", "worker", "is_head", "n_choices"]
    plain = with_source(msgs, sources, dense=dense)
    parts = [compare(msgs, n, sources=sources, dense=dense, **options), key_grouping(plain, n).withColumn("scheme", F.lit("key_grouping")), shuffle_grouping(plain, n, sources).withColumn("scheme", F.lit("shuffle_grouping"))]
    return reduce(DataFrame.unionByName, [p.select(*names) for p in parts])


def imbalance_by_scale(msgs: DataFrame, workers: list[int], dense: bool = True, schemes=COMPARED) -> DataFrame:
    """``(workers, scheme, imbalance)``."""
    return reduce(DataFrame.unionByName, [metrics.imbalance(compare(msgs, n, schemes, dense=dense), n, ["scheme"]).withColumn("workers", F.lit(n)) for n in workers])


def threshold_sweep(msgs: DataFrame, n: int, dense: bool = True) -> DataFrame:
    """``(theta, scheme, imbalance)`` of any worker and head round robin over the thresholds: one pass."""
    grid = [(k, t) for k in ("any_worker", "head_round_robin") for t in bounds.theta_grid(n)]
    rows = route_many(msgs, [Scheme(k, t, name=f"{k}@{float(t * n):.4f}") for k, t in grid], n, dense=dense)
    out = metrics.imbalance(rows, n, ["scheme"])
    return out.select(F.substring_index("scheme", "@", -1).cast("double").alias("theta_n"), F.substring_index("scheme", "@", 1).alias("scheme"), "imbalance")


def head_curve(spark: SparkSession, workers: list[int], z_grid: list[float], keys: int) -> DataFrame:
    """``(workers, z, theta_n, head_size)`` of exact Zipf shares at both ends of the range of thresholds."""
    return grids.exact_head_sizes(spark, workers, z_grid, keys)


def choice_curve(spark: SparkSession, workers: list[int], z_grid: list[float], keys: int, eps: float = bounds.EPS) -> DataFrame:
    """``(workers, z, head_size, start, d, fraction)``: the computed number of choices over the skew."""
    return choices_over_skew(grids.analytic(spark, workers, z_grid, keys, eps=eps))


def choices_over_skew(found: DataFrame) -> DataFrame:
    """The same of what ``grids.analytic`` or ``grids.measured`` gives."""
    found = found.where("scheme = 'tuned'")
    return found.select("workers", "z", "head_size", F.greatest(F.lit(2), F.ceil(F.col("p1") * F.col("workers"))).cast("int").alias("start"), "d", (F.col("d") / F.col("workers")).alias("fraction"))


def memory_curve(spark: SparkSession, workers: list[int], z_grid: list[float], keys: int, messages: int) -> DataFrame:
    """``(workers, z, scheme, vs_two_choice, vs_shuffle)``: estimated state in percent more than the two baselines."""
    return grids.analytic(spark, workers, z_grid, keys, messages).select("workers", "z", "scheme", "vs_two_choice", "vs_shuffle")


def choices_against_minimum(msgs: DataFrame, workers: list[int]) -> DataFrame:
    """``(workers, computed, minimum, gap)``: the computed d beside the least that balances as well as any worker."""
    from skewroute.operators.route import empirical_min_d

    rows = []
    for n in workers:
        d = with_known_head(msgs, Scheme("tuned"), n).d
        least, _ = empirical_min_d(msgs, n)
        rows.append((n, d, least, d - least))
    return msgs.sparkSession.createDataFrame(rows, "workers int, computed int, minimum int, gap int")


def queue_comparison(msgs: DataFrame, n: int, sources: int, service_us: int, utilisation: float = 1.0) -> DataFrame:
    """``(scheme, messages, makespan_us, per_second, max_avg_us, p50_us, p95_us, p99_us)`` of all schemes in the queue model.

    Messages come at ``utilisation`` of what all workers can serve together.
    """
    routed = queueing.arrivals(with_baselines(msgs, n, sources), utilisation * n * 1e6 / service_us)
    timed = queueing.simulate(routed, service_us, ["scheme"])
    return queueing.throughput(timed, ["scheme"]).join(queueing.latency_summary(timed, ["scheme"]), "scheme")


def run_grid(spark: SparkSession, grid: ExperimentGrid, schemes=COMPARED) -> DataFrame:
    """``(k, z, workers, scheme, messages, imbalance)`` of the whole grid in one job."""
    streams = grids.zipf_streams(spark, grid.messages, [(k, z) for k in grid.keys for z in grid.z])
    found = grids.imbalances(grids.loads(streams, [(n, Scheme(k, eps=grid.eps)) for n in grid.workers for k in schemes], grid.sources))
    name = F.split("stream", "/")
    return found.select(name[0].cast("int").alias("k"), name[1].cast("double").alias("z"), "workers", "scheme", "messages", "imbalance")


def real_streams(spark: SparkSession, folder: str) -> dict[str, tuple[DataFrame, bool]]:
    """Streams with natural or drifting skew, and whether their order is dense."""
    return {
        "words": (tables.token_messages(spark, folder), False),
        "visits": (zipf.visits(spark, folder), False),
        "hosts": (tables.hosts(spark, folder), True),
        "links": (tables.links(spark, folder), False),
        "drift": (zipf.drift_events(spark, folder, 1500, 1.0).select("seq", "key"), True),
        "languages": (tables.read_table(spark, folder, "documents").select(F.col("doc_id").alias("seq"), F.col("lang").alias("key")), True),
    }


def best_known(scheme: Scheme, msgs: DataFrame, n: int) -> Scheme:
    return replace(with_known_head(msgs, scheme, n), name=scheme.label)
