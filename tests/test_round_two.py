"""What the second round of findings asked for."""

import hashlib
from fractions import Fraction

import numpy as np
import pytest
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from skewroute.operators import sketch
from skewroute.operators.kernel import Fleet, Router, Scheme
from skewroute.operators.route import with_source
from skewroute.plans import catalog, grids
from skewroute.sources import tables, zipf


def test_spilled_counters_are_exact_beyond_their_capacity(spark):
    msgs = spark.range(20_000).select(F.col("id").alias("seq"), F.when(F.col("id") % 7 > 0, (F.col("id") * F.col("id") % 997).cast("string")).alias("key"))
    found = sketch.merge_spilled(sketch.spilled_per_source(with_source(msgs, 5), 20)).collect()
    want = {r["key"]: r["count"] for r in msgs.groupBy("key").count().collect()}
    assert len(want) > 100 and {r["key"]: r["cnt"] for r in found} == want
    assert len(found) == len(want) and all(r["err"] == 0 and r["n_seen"] == 20_000 for r in found)


def test_fleet_gives_the_loads_of_routers_that_run_alone():
    draw = np.random.default_rng(3)
    keys = [None if k == 7 else str(k) for k in np.minimum(draw.zipf(1.4, 12_000), 3000).tolist()]
    h = {i: np.array([int(hashlib.md5(f"{i}:{chr(0) + 'null' if k is None else k}".encode()).hexdigest()[:8], 16) for k in keys]) for i in (1, 2)}
    kinds = [Scheme("two_choice"), Scheme("tuned"), Scheme("any_worker"), Scheme("head_round_robin"), Scheme("tuned", distinct_candidates=True), Scheme("any_worker", decay=0.5, decay_every=200)]
    kinds += [Scheme("uniform", d=3), Scheme("tuned", tie="rotate"), Scheme("any_worker", warmup=50), Scheme("fixed_head", d=9, head=("1", "2")), Scheme("any_worker", head=("1", "2")), Scheme("tuned", capacity=11, theta=Fraction(1, 10))]
    points = [(n, s) for n in (2, 5, 20, 100) for s in kinds]
    fleet = Fleet(points, 1)
    for lo in range(0, len(keys), 1700):  # batches do not matter
        fleet.run(keys[lo : lo + 1700], h[1][lo : lo + 1700], h[2][lo : lo + 1700])
    for (n, s), r, heads in zip(points, fleet.routers, fleet.heads, strict=True):
        alone = Router(s, n, 1)
        w, hot, _ = alone.run(keys, (h[1] % n).tolist(), (h[2] % n).tolist())
        assert alone.load == r.load and (alone.d, alone.cursor) == (r.d, r.cursor), (n, s)
        assert heads == np.bincount([x for x, is_head in zip(w, hot, strict=True) if is_head], minlength=n).tolist(), (n, s)
        if alone.online:
            assert (alone.sketch.counts, alone.sketch.total) == (r.sketch.counts, r.sketch.total)


@pytest.mark.parametrize("name", ["expected_union", "head_size_curve", "choice_fraction_curve", "choice_prefixes_ablation", "memory_claims", "memory_curve", "computed_against_minimum_d", "distinct_candidates_ablation", "key_count_has_no_effect", "saturated_cluster", "skew_sweep"])
def test_query_follows_its_table(spark, tmp_path, name):
    """Without the given table there is nothing to compute."""
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        catalog.QUERIES[name](spark, f"file://{tmp_path}").collect()


def test_rows_are_dealt_over_the_streams_whole(spark, folder):
    grid = [(100, 1.0), (1000, 1.4), (50, 0.3)]
    streams = grids.table_streams(spark, folder, grid)
    assert streams.count() == tables.read_table(spark, folder, "lineitem").count()
    assert {r["stream"] for r in streams.select("stream").distinct().collect()} == {f"{k}/{z}" for k, z in grid}


def test_drawn_counts_are_those_of_the_stream(spark, folder):
    counts = grids.drawn_counts(spark, folder, 100, [1.0, 1.4])
    for z in (1.0, 1.4):
        want = {int(r["key"]): r["count"] for r in zipf.zipf_events(spark, folder, 100, z).groupBy("key").count().collect()}
        assert {r["key"]: r["f"] for r in counts.where(F.col("z") == z).collect()} == want


def test_token_pairs_are_combined_before_they_are_exchanged(spark, folder):
    plan = catalog.token_pairs(spark, folder)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == plan.count("Exchange") == 3 and "Window" not in plan
    after = plan[: plan.index("MapInArrow")]  # a plan is printed from its end
    assert after.count("partial_count") == 1 and "seq" not in after[: after.index("partial_count")].split("Exchange")[-1].split("\n")[0]
