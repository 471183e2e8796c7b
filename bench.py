"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import statistics
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from skewroute.functions import bounds
from skewroute.operators import aggregate, blocks, heavy, metrics
from skewroute.operators.blocks import throughput_probe
from skewroute.operators.kernel import Scheme
from skewroute.operators.route import route, route_many, with_known_head
from skewroute.plans import experiments, grids
from skewroute.sources import zipf
from skewroute.sources.tables import token_messages

N = 20
REPEATS = 3
#: The timed experiment's skews, and the messages that each is given here: its own number at the highest one.
SKEWS, MESSAGES = (1.4, 1.7, 2.0), {1.4: 2 * 10**5, 1.7: 2 * 10**5, 2.0: 2 * 10**6}


def timed(fn) -> tuple[float, object]:
    began = time.time()
    out = fn()
    return time.time() - began, out


def main() -> None:
    folder, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    n = int(cpus)
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("skewroute-bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    words = token_messages(spark, folder).repartition(n).cache()
    m = words.count()
    head = heavy.exact_head(words, bounds.default_theta(N))
    seconds: dict[str, float] = {}
    facts: dict[str, object] = {"messages": m}

    def run(name: str, fn, repeats: int = 3) -> None:
        """Median of some runs after one that does not count."""
        out = fn()
        took = [timed(fn)[0] for _ in range(repeats)]
        seconds[name] = round(statistics.median(took), 3)
        if out is not None:
            facts[name] = out

    def balance(routed):
        return round(metrics.imbalance(routed, N).first()[0], 6)

    for kind in ("key_grouping", "shuffle_grouping", "two_choice", "tuned", "any_worker", "head_round_robin"):
        run(f"route_{kind}", lambda k=kind: balance(route(words, k, N, 8, dense=False, family="xx")), 1)
    for kind in ("shuffle_grouping", "two_choice", "tuned", "any_worker"):
        run(f"route_{kind}_splits", lambda k=kind: balance(route(words, k, N, "splits", family="xx")))
    facts["messages_a_second"] = {k: round(m / seconds[k]) for k in seconds}
    known = with_known_head(words, Scheme("any_worker"), N)
    run("route_blocks_1024", lambda: balance(blocks.route_blocks(words, known, N, 1024, 8, dense=False, family="xx")), 1)
    run("route_salted", lambda: balance(blocks.salted_plan(words, head, N, N)), 1)
    run("route_planned", lambda: balance(blocks.planned_routing(words, head, N, N, family="xx")), 1)
    run("exact_head", lambda: head.count())
    run("balanced_word_count", lambda: aggregate.balanced_agg(route(words, "two_choice", 8, 8, dense=False, family="xx"), 8, {"n": ("count", "seq")}).count(), 1)
    run("plain_word_count", lambda: heavy.frequencies(words).count())

    # Costly work for each row, a worker a core: what balance is worth. Rows are routed beforehand, so the work alone is timed.
    for z in SKEWS:
        skewed = zipf.zipf_range(spark, 200_000, 10_000, z, partitions=n).cache()
        skewed.count()
        took: dict[str, float] = {}
        for kind in ("key_grouping", "two_choice", "tuned", "any_worker", "shuffle_grouping"):
            placed = aggregate.place(route(skewed, k := kind, n, n).select("worker", "key"), n).cache()
            placed.count()
            work = placed.mapInPandas(throughput_probe, "n long").agg(F.sum("n"))
            work.first()
            took[k] = statistics.median(timed(work.first)[0] for _ in range(REPEATS))
            seconds[f"costly_{z}_{k}"] = round(took[k], 3)
            placed.unpersist()
        facts[f"costly_gain_{z}"] = {"over_two_choice": round(took["two_choice"] / took["tuned"], 2), "over_key_grouping": round(took["key_grouping"] / took["tuned"], 2), "of_shuffle": round(took["shuffle_grouping"] / took["tuned"], 2)}
        skewed.unpersist()

    # The queue model of the timed experiment.
    for z in SKEWS:
        took_q, rows = timed(lambda z=z: experiments.queue_comparison(zipf.zipf_range(spark, MESSAGES[z], 10_000, z, partitions=n), 80, 48, 1000).collect())
        seconds[f"queue_model_{z}"] = round(took_q, 3)
        facts[f"queue_model_{z}"] = {r["scheme"]: [round(r["per_second"]), round(r["p99_us"])] for r in rows}
    run("sweep_schemes_one_pass", lambda: route_many(words.where("seq % 4 = 0"), [Scheme(k) for k in experiments.COMPARED], 50, 8, dense=False).count(), 1)
    streams = grids.zipf_streams(spark, 10_000, [(k, z) for k in (10**4, 10**5, 10**6) for z in (0.4, 0.8, 1.2, 1.6, 2.0)])
    run("grid_300_points", lambda: grids.imbalances(grids.loads(streams, grids.every(experiments.COMPARED, [5, 10, 20, 50, 100]))).count(), 1)
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": folder.rsplit("sf", 1)[-1], "facts": facts}))
    spark.stop()


if __name__ == "__main__":
    main()
