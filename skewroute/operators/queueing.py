"""A queue model of a routed stream: each worker serves its messages one by one in constant time.

It is a model, not a measurement of a cluster. The completion of the i-th message of a worker is i services after the
latest, over the messages before it, of arrival less the services due by then: a running maximum, taken by slices of time.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def arrivals(routed: DataFrame, rate: float, order: str = "seq") -> DataFrame:
    """Add ``arrival_us`` by a dense order at ``rate`` messages a second."""
    return routed.withColumn("arrival_us", F.floor(F.col(order) * F.lit(1e6 / rate)).cast("long"))


def simulate(routed: DataFrame, service_us: int, by: list[str] | None = None, order: str = "seq", slice_us: int | None = None) -> DataFrame:
    """Add ``finish_us`` and ``latency_us`` to rows with ``arrival_us``.

    A worker's messages are cut into slices of arrival time (4,096 services each by default), so that no window holds a worker's whole stream. A slice is
    summed up by its number of messages and by the latest of arrival less the services due in it; a window over those, one row a
    worker and slice, gives what each slice inherits, and the rest happens inside slices.
    """
    by, width = by or [], slice_us or 4096 * service_us
    cut = routed.withColumn("_slice", F.floor(F.col("arrival_us") / width))
    own = Window.partitionBy(*by, "worker", "_slice").orderBy("arrival_us", order)
    ranked = cut.withColumn("_j", F.row_number().over(own).cast("long")).withColumn("_slack", F.col("arrival_us") - service_us * (F.col("_j") - 1))
    key = [*by, "worker", "_slice"]
    parts = ranked.groupBy(*key).agg(F.count("*").alias("_c"), F.max("_slack").alias("_m"))
    past = Window.partitionBy(*by, "worker").orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    before = parts.withColumn("_before", F.coalesce(F.sum("_c").over(past), F.lit(0)))
    inherited = before.withColumn("_latest", F.max(F.col("_m") - service_us * F.col("_before")).over(past)).select(*key, "_before", "_latest")
    within = F.max("_slack").over(own.rowsBetween(Window.unboundedPreceding, 0)) - service_us * F.col("_before")
    timed = ranked.join(inherited, key).withColumn("_within", within)
    finish = service_us * (F.col("_before") + F.col("_j")) + F.greatest("_within", F.coalesce("_latest", "_within"))
    out = timed.withColumn("finish_us", finish).withColumn("latency_us", F.col("finish_us") - F.col("arrival_us"))
    return out.select(*routed.columns, "finish_us", "latency_us")


def throughput(simulated: DataFrame, by: list[str] | None = None) -> DataFrame:
    """``(by, messages, makespan_us, per_second)``."""
    out = simulated.groupBy(*(by or [])).agg(F.count("*").alias("messages"), F.max("finish_us").alias("makespan_us"))
    return out.withColumn("per_second", F.col("messages") * 1e6 / F.col("makespan_us"))


def latency_summary(simulated: DataFrame, by: list[str] | None = None, exact: bool = True) -> DataFrame:
    """``(by, max_avg_us, p50_us, p95_us, p99_us)``: the slowest worker's mean, and percentiles over all workers."""
    by = by or []
    means = simulated.groupBy(*by, "worker").agg(F.avg("latency_us").alias("a")).groupBy(*by).agg(F.max("a").alias("max_avg_us"))
    at = F.percentile if exact else F.percentile_approx
    spread = simulated.groupBy(*by).agg(*(at("latency_us", F.lit(p / 100)).alias(f"p{p}_us") for p in (50, 95, 99)))
    return means.join(spread, by) if by else means.join(F.broadcast(spread))
