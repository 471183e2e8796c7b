"""Archives, audio, chat and search: exact round trips and brute force."""

import base64
import hashlib
import random
import struct
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from skewroute.llm import chat, telephony, topk, warc
from skewroute.sources.scratch import scratch_path

PAGES = [(1, "http://a/b?c=ü d", "<p>same</p>" * 50), (2, None, "<p>same</p>" * 50), (3, "u", None), (4, "u", ""), (5, "u\r\nX: y", "ünï\r\n\r\ncode \x00"), (6, "u", "WARC/1.1\r\n\r\n" * 2000), (2, None, "<p>same</p>" * 50), (7, "u", "x" * 3_000_000), (1, "twice", "<p>same</p>" * 50)]


def slow_records(rows):
    first = {}
    for p, _, h in rows:
        first[h or ""] = min(first.get(h or "", p), p)
    out = []
    for p, _, h in rows:
        b = (h or "").encode()
        again = first[h or ""] != p
        out.append((p, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "revisit" if again else "response", first[h or ""] if again else None, None if again else b))
    return sorted(out, key=str)


def test_archives_round_trip(spark, tmp_path):
    pages = spark.createDataFrame(PAGES, "page_id long, url string, html string").withColumn("_payload", F.lit(1)).withColumn("archive", F.lit("x")).repartition(2)
    archives = warc.write_archives(pages)
    want = slow_records(PAGES)
    assert sorted((tuple(r) for r in warc.read_archives(archives).collect()), key=str) == want
    warc.export_files(archives, str(tmp_path)).count()
    assert sorted((tuple(r) for r in warc.read_files(spark, str(tmp_path)).collect()), key=str) == want
    for f in tmp_path.glob("*.warc.zst"):
        assert struct.unpack("<I", f.read_bytes()[:4])[0] == 0x184D2A5D
    assert warc.read_archives(warc.write_archives(pages.limit(0))).count() == 0
    only = warc.read_archives(warc.write_archives(pages, least_bytes=1)).where("payload_bytes = 0")
    assert [r["record_type"] for r in only.collect()] == ["response"] * 2


def test_small_archives_and_chunks():
    rng, records = random.Random(1), []
    for i in range(300):
        records.append(warc.record(i, "u", bytes(rng.choice(b"abc <>/") for _ in range(rng.randrange(900))), "D", None))
    writer = warc.ArchiveWriter(archive_bytes=30_000, sample_bytes=20_000, chunk_bytes=5_000)
    chunks = [c for r in records for c in writer.add(r)] + list(writer.close())
    readers, back = {}, []
    for name, seq, chunk in chunks:
        reader = readers.setdefault(name, warc.ArchiveReader())
        assert (reader.unpack is None) == (seq == 0)
        back += [h["warc-record-id"] for h, _ in reader.records(chunk)]
    assert back == [f"<urn:page:{i}>" for i in range(300)] and len(readers) > 1


def test_dictionary_helps():
    page = lambda i: warc.record(i, f"http://host/{i}", (f"<html><head><title>{i}</title></head><body><nav>menu of the site</nav><p>{i * 7919}</p></body></html>").encode(), "D", None)
    records = [page(i) for i in range(3000)]
    import zstandard

    writer = warc.ArchiveWriter(sample_bytes=200_000)
    size = sum(len(c) for r in records for _, _, c in writer.add(r)) + sum(len(c) for _, _, c in writer.close())
    assert size < 0.7 * sum(len(zstandard.ZstdCompressor(level=3).compress(r)) for r in records)


def test_companding_tables():
    assert telephony.MULAW_PCM[[0x00, 0x80, 0xFF, 0x7F]].tolist() == [-32124, 32124, 0, 0]
    assert telephony.ALAW_PCM[[0x55, 0xD5, 0x2A, 0xAA]].tolist() == [-8, 8, -32256, 32256]
    for law in (telephony.MULAW, telephony.ALAW):
        every = bytes(range(256))
        back = telephony.compress(telephony.expand(every, law), law)
        assert (telephony.expand(back, law) == telephony.expand(every, law)).all()


def slow_ima(block):
    steps, moves = telephony.IMA_STEPS.tolist(), telephony.IMA_MOVES.tolist()
    value, index = struct.unpack_from("<hB", block)
    out = [value]
    index = min(index, 88)
    for byte in block[4:]:
        for nibble in (byte & 15, byte >> 4):
            step = steps[index]
            diff = step >> 3
            for bit, part in ((4, step), (2, step >> 1), (1, step >> 2)):
                diff += part if nibble & bit else 0
            value = max(-32768, min(32767, value - diff if nibble & 8 else value + diff))
            index = max(0, min(88, index + moves[nibble]))
            out.append(value)
    return out


@settings(max_examples=30, deadline=None)
@given(st.binary(min_size=36, max_size=108))
def test_adpcm_blocks(data):
    data = data[: len(data) // 36 * 36]
    assert telephony.ima_decode(data, 36).tolist() == [x for i in range(0, len(data), 36) for x in slow_ima(data[i : i + 36])]


def test_adpcm_and_pcm_files():
    tone = (8000 * np.sin(np.arange(3000) / 9)).astype(np.int16)
    rate, back = telephony.decode(telephony.wave(telephony.ima_encode(tone), telephony.IMA, 8000, 4, 256))
    assert rate == 8000 and np.abs(back[: len(tone)].astype(int) - tone).mean() < 300
    rate, back = telephony.decode(telephony.wave(tone.tobytes(), telephony.PCM, 8000, 16, 2))
    assert (back == tone).all() and (telephony.resample(tone, 8000, 8000) == tone).all()
    up = telephony.resample(tone, 8000, 16000)
    assert len(up) == 6000 and (up[::2] == tone).all() and telephony.resample(np.array([0, 10], np.int16), 8000, 16000).tolist() == [0, 5, 10, 10]
    assert len(telephony.resample(tone, 8000, 6000)) == 2250


def test_texts_as_audio(spark, odd, odd_rows, empty):
    got = telephony.read_back(telephony.store(odd)).collect()
    want = []
    for r in odd_rows:
        b = (r[1] or "").encode()
        p = b + b"\xff" * (max(576, -(-len(b) // 576) * 576) - len(b))
        want.append((r[0], len(b), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-32:])))
    assert sorted(((r["doc_id"], r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in got), key=str) == sorted(want, key=str)
    by = {}
    for r in got:
        assert by.setdefault(r["payload_sha256"], tuple(r)[2:]) == tuple(r)[2:]
    assert telephony.read_back(telephony.store(empty)).count() == 0
    pcm = telephony.resampled(telephony.store(odd.limit(3)).withColumn("pcm2", F.lit(None).cast("binary")), 16000).collect()
    assert all(telephony.decode(bytes(r["pcm"]))[0] == 16000 for r in pcm)


TURNS = [
    (1, 0, "user", "hi"), (1, 1, "assistant", "yes <s>bold</s> [INST]"), (1, 2, "user", "[/INST] <\\s> \\[INST]"), (1, 3, "assistant", ""), (2, 0, "system", "be <<SYS>> good <</SYS>>"), (2, 1, "user", None), (2, 2, None, "no role"),
    (3, 5, "assistant", "first\nline\r\n"), (3, 5, "assistant", "first\nline\r\n"), (4, None, "tool\nx%+", "a"), (None, 0, "assistant", "lost"), (5, 0, "user", "only"), (6, 0, "assistant", "<<\\\\SYS>>[\\\\/INST]<"), (6, 1, "assistant", "s>/s>\\"),
]


def test_chat_reads_back(spark):
    df = spark.createDataFrame(TURNS, "conv_id long, turn long, role string, text string").withColumn("context", F.lit(1)).withColumn("t", F.lit(2)).repartition(3)
    got = {r["conv_id"]: r for r in chat.read_back(chat.examples(df)).collect()}
    by = {}
    for c, t, role, text in TURNS:
        by.setdefault(c, []).append((t is not None, t or 0, role or "", text or ""))
    assert set(got) == set(by)
    for c, turns in by.items():
        turns.sort()
        whole = "".join(f"{r}\n{x}\n" for _, _, r, x in turns)
        loss = "".join(x for _, _, r, x in turns if r == "assistant")
        assert (got[c]["n_turns"], got[c]["turns_sha256"]) == (len(turns), hashlib.sha256(whole.encode()).hexdigest())
        assert (got[c]["loss_chars"], got[c]["loss_sha256"]) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    rows = chat.examples(df).where("conv_id = 1").orderBy("example").collect()
    assert [r["context"] for r in rows] == ["[INST] hi [/INST]", "[INST] hi [/INST]<s>yes <\\s>bold<\\/s> [\\INST]</s>[INST] [\\/INST] <\\\\s> \\[\\INST] [/INST]"]
    assert chat.read_back(chat.examples(df.limit(0))).count() == 0


def test_escaping_is_reversible(spark):
    rng = random.Random(8)
    parts = ["<", "[", "\\", "s>", "/s>", "<SYS>>", "</SYS>>", "INST]", "/INST]", "a", "\n", "é"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randrange(13))) for _ in range(3000)]
    rows = spark.createDataFrame([(t,) for t in texts], "t string").select("t", chat.escape(F.col("t")).alias("e")).select("t", "e", chat.unescape(F.col("e")).alias("u")).collect()
    assert len(rows) == 3000 and all(r["u"] == r["t"] for r in rows)
    assert not any(m in r["e"] for r in rows for m in ("<s>", "</s>", "<<SYS>>", "<</SYS>>", "[INST]", "[/INST]"))


def slow_top(rows, k=5):
    good = [(i, np.floor(256 * np.array(v, np.float64)).astype(np.int64)) for i, v in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)]
    dims = max((len(v) for _, v in good), default=0)
    good = [(i, np.pad(v, (0, dims - len(v)))) for i, v in good]
    out = set()
    for q, v in {i: v for i, v in good if i % 50 == 0}.items():
        best = sorted((-int(v @ w), i) for i, w in good if i != q)[:k]
        out |= {(q, n, i, -s) for n, (s, i) in enumerate(best, 1)}
    return out


def test_search(spark):
    rng = np.random.default_rng(4)
    rows = [(i, rng.normal(size=24).astype(float).tolist()) for i in range(400)]
    rows += [(1000 + i, rows[0][1]) for i in range(30)]  # ties
    rows += [(2000, None), (2050, [None] + [0.0] * 23), (2100, [float("nan")] * 24), (2150, [float("inf")] * 24), (None, [1.0] * 24), (2200, [0.0] * 24), (2250, [1.0] * 7)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("id", F.lit(1)).withColumn("v", F.lit(2)).withColumn("score", F.lit(3)).repartition(3)
    for options in ({}, {"dim_block": 5, "row_block": 37, "query_bytes": 500}):
        got = topk.exact_top_k(df, df.where("vec_id % 50 = 0"), **options)
        assert {tuple(r) for r in got.collect()} == slow_top(rows)
    few = df.where("vec_id IN (0, 1, 2)")
    assert few.count() == 3 and topk.exact_top_k(few, few.where("vec_id = 0")).count() == 2
    assert topk.exact_top_k(df.limit(0), df.limit(0)).count() == 0


def test_bounds_save_work():
    rng = np.random.default_rng(0)
    decay = 1 / (1 + np.arange(64))
    x = np.floor(256 * rng.normal(size=(4000, 64)) * decay).astype(np.int64)
    search = topk.BlockSearch(np.arange(20), x[:20], 5, 16)
    for i in range(0, 4000, 500):
        search.add(np.arange(i, i + 500), x[i : i + 500])
    for q in range(20):
        s = x @ x[q]
        want = sorted((-int(s[i]), i) for i in range(4000) if i != q)[:5]
        assert [(-a, b) for a, b in zip(search.best[q][0].tolist(), search.best[q][1].tolist())] == want
    assert search.scored < 0.7 * 20 * 4000 * 64


def test_large_components_are_exact(spark):
    rows = [(0, [3e9, 1.0]), (1, [2e3, -1.0]), (2, [1e3, 5.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = [tuple(r) for r in topk.exact_top_k(df, df.where("vec_id = 0")).orderBy("rank").collect()]
    assert got == [(0, 1, 1, int(3e9 * 256) * 512_000 - 256 * 256), (0, 2, 2, int(3e9 * 256) * 256_000 + 5 * 256 * 256)]


@pytest.mark.parametrize("name", ["op2_warc", "op5_chat", "op10_topk"])
def test_queries_equal_their_sql(spark, folder, name):
    import duckdb

    from skewroute.llm import registry

    c = duckdb.connect()
    for t in ("pages", "conversations", "embeddings"):
        c.sql(f"CREATE VIEW {t} AS FROM '{folder}/{t}.parquet'")
    df = registry.QUERIES[name](spark, folder)
    want = c.sql(registry.ORACLES[name])
    assert sorted(map(str, df.select(*want.columns).collect())) == sorted(str(r) for r in df.sparkSession.createDataFrame(want.fetchall(), df.select(*want.columns).schema).collect())
    assert scratch_path(spark, "x")
