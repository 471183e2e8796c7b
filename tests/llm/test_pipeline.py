"""The pipeline: every stage on what its predecessor kept, against the operators' brute-force versions."""

import json
from collections import Counter

import numpy as np
import zlib

import corpus_pipeline
from skewroute.llm import packing, quality
from skewroute.llm.common import materialize, read_table
from tests.llm.test_documents import WORD, slow_components, slow_fingerprint, slow_removal


def test_pipeline_by_brute_force(spark, folder):
    docs = read_table(spark, folder, "documents")
    kept = []
    for name, stage in corpus_pipeline.STAGES:
        out = materialize(stage(spark, docs, folder), name)
        kept.append(out)
        if name != "best_fit_packing":
            assert out.columns == docs.columns
        docs = out
    source = {r["doc_id"]: r for r in read_table(spark, folder, "documents").collect()}
    good, one, cut, mixed, packed = (x.collect() for x in kept)
    told = {r["doc_id"]: r["keep"] for r in quality.classify(read_table(spark, folder, "documents"), read_table(spark, folder, "labels")).collect()}
    assert Counter(map(str, good)) == Counter(str(r) for d, r in source.items() if told[d])

    label = slow_components([slow_fingerprint(r["text"]) for r in good])
    least = {}
    for r, x in zip(good, label):
        least[x] = min(least.get(x, r["doc_id"]), r["doc_id"])
    assert sorted(r["doc_id"] for r in one) == sorted(least.values())
    assert all(str(r) == str(source[r["doc_id"]]) for r in one)

    want = {d: (n, gone, sha) for d, n, gone, sha in slow_removal([(r["doc_id"], r["text"]) for r in one], 50)}
    texts = {r["doc_id"]: r["text"] for r in cut}
    assert set(texts) == {d for d, (n, gone, _) in want.items() if not gone or gone < n}
    for d, t in texts.items():
        assert len(WORD.findall(t or "")) == want[d][0] - want[d][1]
        assert t == source[d]["text"] if not want[d][1] else slow_removal([(d, t)], 50)
    assert any(gone for _, gone, _ in want.values())

    copies = Counter(r["doc_id"] for r in mixed)
    assert all(0 < n <= 3 for n in copies.values()) and all(r["text"] == texts[r["doc_id"]] for r in mixed)
    total = sum(len(WORD.findall(t or "")) for t in texts.values())
    assert abs(sum(len(WORD.findall(r["text"])) for r in mixed) - total) <= 0.05 * total

    from tokenizers import Tokenizer

    tokenizer, pieces = Tokenizer.from_file(packing.tokenizer_path()), Counter()
    for d, n in copies.items():
        ids = tokenizer.encode(texts[d], add_special_tokens=False).ids + [1]
        for k, a in enumerate(range(0, len(ids), 4096)):
            pieces[d, k, a, len(ids[a : a + 4096]), zlib.crc32(np.array(ids[a : a + 4096], "<u4").tobytes())] += n
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in packed) == pieces
    load = Counter()
    for r in packed:
        load[r["sequence_id"]] += r["length"]
    assert max(load.values()) <= 4096 and len(load) <= 1.02 * -(-sum(load.values()) // 4096) + 1


def test_run_gives_the_last_stage(spark, folder):
    rows = corpus_pipeline.run(spark, folder)
    assert rows.count() and "sequence_id" in rows.columns and json.dumps(rows.columns)


def test_stages_take_odd_and_empty_tables(spark, odd, odd_rows, empty, tmp_path):
    labels = [(r[0], 1 if r[0] and r[0] >= 100 else None, 0) for r in odd_rows] + [(1, 0, None), (None, 1, 1)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    for docs in (odd, empty):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, docs, str(tmp_path))
            assert name == "best_fit_packing" or out.columns == docs.columns
            n = out.count()
            assert n if docs is odd else not n
    kept = quality.quality_stage(spark, odd, str(tmp_path))
    assert sum(r["doc_id"] is None for r in kept.select("doc_id").collect()) == 2  # null ids are never rejected by id
