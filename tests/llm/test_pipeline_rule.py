"""The pipeline stage by stage against brute force, with near duplicates as the stage has them: three bits, or five-word shingle sets alike to 0.8."""

import zlib
from collections import Counter

import numpy as np
import pytest

import corpus_pipeline
from skewroute.llm import packing, quality, simhash
from skewroute.llm.common import materialize, read_table
from tests.llm.test_documents import WORD, slow_fingerprint, slow_removal


def slow_groups(texts):
    """The least index of each text's group: every pair is looked at."""
    fps = np.array([slow_fingerprint(t) for t in texts], np.uint64)
    words = [WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")) for t in texts]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set() for w in words]
    near = np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 3
    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a and b and 5 * min(len(a), len(b)) >= 4 * max(len(a), len(b)):
                both = len(a & b)
                if 5 * both >= 4 * (len(a) + len(b) - both):
                    near[i, j] = near[j, i] = True
    label = np.arange(len(texts))
    while (new := np.array([label[near[i]].min() for i in range(len(texts))])).tolist() != label.tolist():
        label = new
    return label.tolist()


@pytest.mark.parametrize("size", ["sf0.001", "sf0.01"])
def test_near_copy_stage_by_brute_force(spark, size):
    docs = read_table(spark, f"/root/testdata/{size}", "documents")
    rows = sorted(docs.collect(), key=lambda r: r["doc_id"])
    label = slow_groups([r["text"] for r in rows])
    kept = simhash.near_copy_stage(spark, docs, "").collect()
    assert sorted(map(str, kept)) == sorted(str(rows[i]) for i in set(label)) and len(kept) < len(rows)


def test_pipeline_under_the_stage_rule(spark, folder):
    docs = read_table(spark, folder, "documents")
    kept = []
    for name, stage in corpus_pipeline.STAGES:
        docs = materialize(stage(spark, docs, folder), name)
        kept.append(docs.collect())
    source = {r["doc_id"]: r for r in read_table(spark, folder, "documents").collect()}
    good, one, cut, mixed, packed = kept
    told = {r["doc_id"]: r["keep"] for r in quality.classify(read_table(spark, folder, "documents"), read_table(spark, folder, "labels")).collect()}
    assert Counter(map(str, good)) == Counter(str(r) for d, r in source.items() if told[d])

    good = sorted(good, key=lambda r: r["doc_id"])
    assert sorted(map(str, one)) == sorted(str(good[i]) for i in set(slow_groups([r["text"] for r in good])))

    want = {d: (n, gone, sha) for d, n, gone, sha in slow_removal([(r["doc_id"], r["text"]) for r in one], 50)}
    texts = {r["doc_id"]: r["text"] for r in cut}
    assert set(texts) == {d for d, (n, gone, _) in want.items() if not gone or gone < n}
    for d, t in texts.items():
        assert len(WORD.findall(t or "")) == want[d][0] - want[d][1] and (want[d][1] or t == source[d]["text"])

    copies = Counter(r["doc_id"] for r in mixed)
    assert all(0 < n <= 3 for n in copies.values()) and all(r["text"] == texts[r["doc_id"]] for r in mixed)
    total = sum(len(WORD.findall(t or "")) for t in texts.values())
    assert abs(sum(len(WORD.findall(r["text"])) for r in mixed) - total) <= 0.05 * total

    from tokenizers import Tokenizer

    tokenizer, pieces, load = Tokenizer.from_file(packing.tokenizer_path()), Counter(), Counter()
    for d, n in copies.items():
        ids = tokenizer.encode(texts[d], add_special_tokens=False).ids + [1]
        for k, a in enumerate(range(0, len(ids), 4096)):
            pieces[d, k, a, len(ids[a : a + 4096]), zlib.crc32(np.array(ids[a : a + 4096], "<u4").tobytes())] += n
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in packed) == pieces
    for r in packed:
        load[r["sequence_id"]] += r["length"]
    assert max(load.values()) <= 4096 and len(load) <= 1.02 * -(-sum(load.values()) // 4096) + 1
