"""Findings of the first review: what the code left undone, on rows that showed it."""

import random

import numpy as np

import corpus_pipeline
from skewroute.llm import quality, simhash
from skewroute.llm.common import read_table
from tests.llm.conftest import SCHEMA, prose


def near_copy(rng, words, edits):
    out = list(words)
    for at in rng.sample(range(len(out)), edits):
        out[at] = f"changed{rng.randrange(10**6)}"
    return " ".join(out)


def test_stage_links_near_copies(spark):
    rng = random.Random(3)
    rows, texts = [], []
    for group in range(20):
        words = [f"w{rng.randrange(10**6)}" for _ in range(300)]
        texts += [" ".join(words), near_copy(rng, words, 5), " ".join(f"w{rng.randrange(10**6)}" for _ in range(150)) + " " + " ".join(words[:150])]
        rows += [(3 * group + k, texts[-3 + k], "en", "a", 1) for k in range(3)]
    docs = spark.createDataFrame(rows, SCHEMA)
    sets = [set(simhash.shingle_set(t).tolist()) for t in texts]
    copies = {j for j in range(len(rows)) if any(len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) for i in range(j))}
    fps = [simhash.fingerprint(t) for t in texts]
    assert len(copies) == 20 and sum((fps[j] ^ fps[j - 1]).bit_count() > 3 for j in copies) > 5
    kept = {r["doc_id"] for r in dict(corpus_pipeline.STAGES)["simhash_near_dedup"](spark, docs, "").select("doc_id").collect()}
    assert kept == set(range(len(rows))) - copies


def test_bands_meet_at_the_similarity():
    rng = np.random.default_rng(0)
    met = [False, True]
    for _ in range(200):
        x = rng.integers(0, 1 << 63, 900, dtype=np.uint64)
        a, b = simhash.bands(x[:800]), simhash.bands(np.r_[x[:711], x[800:889]])  # 711 of 889: 0.8
        met[0] |= bool((a == simhash.bands(rng.integers(0, 1 << 63, 800, dtype=np.uint64))).any())
        met[1] &= bool((a == b).any())
    assert met == [False, True]


def test_repetition_is_not_quality(spark):
    rng = random.Random(4)
    rows = [(i, prose(rng, rng.randrange(20, 200)), "en", "a", 1) for i in range(300)]
    junk = [(1000, "the " * 400, "en", "a", 1), (1001, "stream of state\n" * 60, "en", "a", 1), (1002, (prose(rng, 12) + ".\n") * 50, "en", "a", 1)]
    labels = spark.createDataFrame([(r[0], 1, 0) for r in rows], "doc_id long, quality int, toxic int")
    keep = {r["doc_id"]: r["keep"] for r in quality.classify(spark.createDataFrame(rows + junk, SCHEMA), labels).collect()}
    assert not any(keep[r[0]] for r in junk) and sum(keep[r[0]] for r in rows) >= 295


def test_repeated_words_of_the_given_table(spark):
    folder = "/root/testdata/sf0.01"
    docs = {r["doc_id"]: (r["text"] or "").split() for r in read_table(spark, folder, "documents").collect()}
    told = quality.op8_quality(spark, folder).join(read_table(spark, folder, "labels"), "doc_id").collect()
    repeats = [r for r in told if r["quality"] == 0 and len(set(docs[r["doc_id"]])) <= 0.1 * len(docs[r["doc_id"]])]
    assert len(repeats) >= 5 and not any(r["keep"] for r in repeats)


def test_distinct_counts_by_stretch():
    codes = np.array([0, 0, 1] * 1000 + [2], np.int64)
    assert quality._distinct(codes, np.array([3000, 0, 1]), 3).tolist() == [6, 0, 1]


def test_stage_rejects_rows_without_an_id(spark, odd_rows, tmp_path):
    junk = [(None, "the " * 400, "en", "a", 1)]
    labels = [(r[0], 1, 0) for r in odd_rows if r[0] and r[0] >= 100]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    kept = quality.quality_stage(spark, spark.createDataFrame(odd_rows + junk, SCHEMA), str(tmp_path)).collect()
    assert sum(r["doc_id"] is None for r in kept) == 2 and junk[0][1] not in {r["text"] for r in kept}
