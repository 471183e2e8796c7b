"""Perplexity filter: an interpolated modified Kneser-Ney model over UTF-16 code units, counted on trusted texts.

Documents are dealt into chunks by a hash of their id. A first pass counts the 4-grams of trusted documents and notes which
4-grams each chunk asks for; their probabilities come from joins of count tables sharded by n-gram; a second pass gives
each chunk the probabilities it asked for and scores its documents. So neither the model nor a document's n-grams ever
have to fit one place: a task holds one chunk of texts and the distinct 4-grams in it. Texts travel compressed.
A document is rejected if its log-perplexity exceeds a high quantile of trusted documents of its language that the
counts have not seen. Text that repeats itself is easy to foretell, so a document is also rejected if it has far fewer
distinct 4-grams for its length than nearly all of those trusted documents.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from skewroute.llm.common import input_partitions, materialize, read_table, release_memory, tidy

ORDER = 4
#: Quantile of trusted held-out documents of a language at its threshold, slack in nats per unit, and what the mean of
#: a text of one unit may stray by more.
QUANTILE = 0.99
SLACK = 0.05
STRAY = 2.0
#: Units of the stretches whose distinct 4-grams are counted, so that variety does not fall with length; and the part of
#: the trusted documents' low quantile (1 - QUANTILE) that a text must reach.
STRETCH = 1024
LEAST_VARIETY = 0.5
#: Languages with fewer held-out trusted documents take the quantile of all languages together.
LEAST_HELD = 40
#: Units that are hashed at a time; bounds memory only.
_UNITS = 1_000_000
_MASK = {3: (1 << 48) - 1, 2: (1 << 32) - 1, 1: (1 << 16) - 1}


def _compressed(docs: DataFrame, chunks: int) -> DataFrame:
    """``(chunk, id, r, lang, z)``: one row for each document, its text compressed for the exchange."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=1)
        for b in batches:
            z = [pack.compress(t.encode("utf-16-le", "surrogatepass")) if t else None for t in b.column("t").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("chunk", "id", "r", "lang")), pa.array(z, pa.binary())], ["chunk", "id", "r", "lang", "z"])

    source = docs.select(_chunk(F.coalesce(F.col("doc_id").cast("long"), F.xxhash64("text")), chunks).alias("chunk"), F.col("doc_id").cast("long").alias("id"), F.xxhash64("text").alias("r"), F.col("lang").cast("string").alias("lang"), F.col("text").alias("t"))
    return source.mapInArrow(tidy(run), "chunk int, id long, r long, lang string, z binary")


def _chunk(doc_id: Column, chunks: int) -> Column:
    return F.pmod(F.xxhash64(doc_id.cast("long")), F.lit(chunks)).cast("int")


def _parts(table: pa.Table) -> Iterator[tuple[slice, np.ndarray, np.ndarray]]:
    """Runs of documents of some million units: their rows, the 4-gram ending at each unit, and units per document."""
    unpack, column, start, held, sizes, units = zstandard.ZstdDecompressor(), table.column("z"), 0, [], [], 0
    for row, z in enumerate(column):
        raw = np.frombuffer(unpack.decompress(z.as_py()), "<u2") if z.is_valid else np.zeros(0, np.uint16)
        held.append(np.r_[np.zeros(ORDER - 1, np.uint16), raw])
        sizes.append(len(raw))
        units += len(raw)
        if units >= _UNITS or row == len(column) - 1:
            x = np.concatenate(held).astype(np.uint64)
            keys = x[3:] | x[2:-1] << np.uint64(16) | x[1:-2] << np.uint64(32) | x[:-3] << np.uint64(48)
            # Grams that begin in one document's units and end in the next one's padding are not of either.
            lengths = np.array([len(h) for h in held])
            ends = np.cumsum(lengths)
            stay = np.ones(len(x), bool)
            for pad in range(ORDER - 1):
                stay[ends - lengths + pad] = False
            yield slice(start, row + 1), keys[stay[3:]].view(np.int64), np.array(sizes, np.int64)
            start, held, sizes, units = row + 1, [], [], 0


def _count_chunk(docs: pa.Table, trusted: pa.Table) -> pa.Table:
    """Distinct 4-grams of a chunk and how often trusted documents of it hold each (0: only asked for)."""
    known, counts = pd.Index([], dtype="int64"), np.zeros(0, np.int64)
    ids = set(trusted.column("id").to_pylist())
    for rows, keys, sizes in _parts(docs):
        trust = np.array([i in ids for i in docs.column("id")[rows.start : rows.stop].to_pylist()], bool)
        codes, found = pd.factorize(keys)
        n = np.bincount(codes, weights=np.repeat(trust, sizes), minlength=len(found)).astype(np.int64)
        at = known.get_indexer(found)
        np.add.at(counts, at[at >= 0], n[at >= 0])
        known, counts = known.append(pd.Index(found[at < 0])), np.r_[counts, n[at < 0]]
    release_memory()
    chunk = docs.column("chunk")[0].as_py() if docs.num_rows else 0
    return pa.table({"chunk": pa.array(np.full(len(known), chunk, np.int32)), "key": pa.array(known.to_numpy()), "n": pa.array(counts)})


def _distinct(codes: np.ndarray, sizes: np.ndarray, known: int) -> np.ndarray:
    """Of documents laid end to end: each one's distinct codes (below ``known``), counted anew in every stretch. Stretches of like width are sorted side by side."""
    pieces = -(-sizes // STRETCH)
    of = np.repeat(np.arange(len(sizes)), pieces)
    nth = np.arange(len(of)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    start = (np.cumsum(sizes) - sizes)[of] + nth * STRETCH
    length = np.minimum(sizes[of] - nth * STRETCH, STRETCH)
    found, codes = np.zeros(len(of), np.int64), codes.astype(np.int32 if known < 1 << 31 else np.int64)
    for low, width in ((0, 128), (128, 384), (384, STRETCH)):
        own = np.flatnonzero((length > low) & (length <= width))
        for i in range(0, len(own), 2048):
            rows = own[i : i + 2048]
            at = start[rows][:, None] + np.arange(width)
            inside = np.arange(width) < length[rows][:, None]
            # Places beyond the end repeat the first code, so they add none.
            laid = np.sort(np.where(inside, codes[np.minimum(at, len(codes) - 1)], codes[start[rows]][:, None]), axis=1)
            found[rows] = 1 + (laid[:, 1:] != laid[:, :-1]).sum(axis=1)
    return np.bincount(of, weights=found, minlength=len(sizes)).astype(np.int64)


def _score_chunk(docs: pa.Table, answers: pa.Table) -> pa.Table:
    """Mean negative log probability of each document of a chunk, and distinct 4-grams per unit in stretches of it."""
    index, logp = pd.Index(answers.column("key").to_numpy()), answers.column("logp").to_numpy()
    total, count, distinct = np.zeros(docs.num_rows), np.zeros(docs.num_rows, np.int64), np.zeros(docs.num_rows)
    for rows, keys, sizes in _parts(docs):
        codes = index.get_indexer(keys)
        sums = np.r_[0.0, np.cumsum(-logp[codes])]
        ends = np.cumsum(sizes)
        distinct[rows] = _distinct(codes, sizes, len(index))
        total[rows], count[rows] = sums[ends] - sums[ends - sizes], sizes
    release_memory()
    with np.errstate(invalid="ignore"):
        mean, variety = (pa.array(x / count, mask=count == 0) for x in (total, distinct))
    return pa.table({"id": docs.column("id"), "r": docs.column("r"), "lang": docs.column("lang"), "units": pa.array(count), "nats": mean, "variety": variety})


def _level(counts: DataFrame, name: str) -> tuple[DataFrame, list[float]]:
    """Of ``(key, c)`` grams of one order: per context the total and the count classes, and the three discounts."""
    ctx = counts.groupBy(F.shiftrightunsigned("key", 16).alias(f"{name}_ctx")).agg(
        F.sum("c").alias(f"{name}_total"), *(F.count_if(F.col("c") == k).alias(f"{name}_n{k}") for k in (1, 2)), F.count_if(F.col("c") >= 3).alias(f"{name}_n3")
    )
    n = counts.agg(*(F.count_if(F.col("c") == k) for k in (1, 2, 3, 4))).first()
    y = n[0] / max(n[0] + 2 * n[1], 1)
    # Where a count class is empty the discount falls back to half of its bound.
    return ctx, [min(k, max(0.05, k - (k + 1) * y * n[k] / n[k - 1])) if n[k] and n[k - 1] else k / 2 for k in (1, 2, 3)]


def probabilities(keys: DataFrame) -> DataFrame:
    """``(key, logp)`` of every asked 4-gram from ``(key, n)``: joins of count tables on n-gram and context."""
    c4 = keys.where("n > 0").select("key", F.col("n").alias("c"))

    def continued(grams: DataFrame, order: int) -> DataFrame:
        return grams.groupBy(F.col("key").bitwiseAND(F.lit(_MASK[order])).alias("key")).agg(F.count("*").alias("c"))

    c3 = materialize(continued(c4, 3), "c3")
    c2 = materialize(continued(c3, 2), "c2")
    c1 = materialize(continued(c2, 1), "c1")
    cuts: dict[str, list[float]] = {}
    out = keys.withColumnRenamed("n", "g4_c").withColumn("g4_ctx", F.shiftrightunsigned("key", 16))
    for name, counts, mask in (("g4", c4, None), ("g3", c3, _MASK[3]), ("g2", c2, _MASK[2])):
        ctx, discounts = _level(counts, name)
        if mask is not None:
            gram = F.col("key").bitwiseAND(F.lit(mask))
            out = out.withColumn(f"{name}_key", gram).withColumn(f"{name}_ctx", F.shiftrightunsigned(f"{name}_key", 16))
            out = out.join(counts.select(F.col("key").alias(f"{name}_key"), F.col("c").alias(f"{name}_c")), f"{name}_key", "left")
        out = out.join(ctx, f"{name}_ctx", "left")
        cuts[name] = discounts
    total = c1.agg(F.sum("c")).first()[0] or 0
    out = out.withColumn("g1_key", F.col("key").bitwiseAND(F.lit(_MASK[1]))).join(c1.select(F.col("key").alias("g1_key"), F.col("c").alias("g1_c")), "g1_key", "left")
    # Units: continuation counts, one more for any unit never seen, of all 65,536 that there are.
    p = (F.coalesce("g1_c", F.lit(0)) + 1 / 65536.0) / (total + 1)
    for name in ("g2", "g3", "g4"):
        c = F.coalesce(f"{name}_c", F.lit(0))
        d1, d2, d3 = cuts[name]
        cut = F.when(c >= 3, d3).when(c == 2, d2).when(c == 1, d1).otherwise(0.0)
        left = d1 * F.col(f"{name}_n1") + d2 * F.col(f"{name}_n2") + d3 * F.col(f"{name}_n3")
        p = F.when(F.col(f"{name}_total").isNull(), p).otherwise((F.greatest(c - cut, F.lit(0.0)) + left * p) / F.col(f"{name}_total"))
    return out.select("key", F.log(p).alias("logp"))


def held_out(doc_id: Column) -> Column:
    """A fifth of the trusted documents sets the thresholds and is never counted."""
    return F.pmod(F.xxhash64(doc_id.cast("long"), F.lit("held")), F.lit(5)) == 0


def perplexities(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``(id, r, lang, units, nats, variety, held)``: log-perplexity and variety per unit of every document, materialised."""
    chunks = max(8, 2 * input_partitions(docs))
    trusted = labels.where("quality = 1 AND doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("id")).distinct()
    texts = _compressed(docs, chunks)
    counted = trusted.where(~held_out(F.col("id"))).withColumn("chunk", _chunk(F.col("id"), chunks)).select("chunk", "id")
    asked = materialize(texts.groupBy("chunk").cogroup(counted.groupBy("chunk")).applyInArrow(_count_chunk, "chunk int, key long, n long"), "grams")
    keys = materialize(asked.groupBy("key").agg(F.sum("n").alias("n")), "keys")
    answers = asked.select("chunk", "key").join(probabilities(keys), "key").select("chunk", "key", "logp")
    scored = texts.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(_score_chunk, "id long, r long, lang string, units long, nats double, variety double")
    held = trusted.where(held_out(F.col("id"))).withColumn("held", F.lit(True))
    return materialize(scored.join(held, "id", "left"), "perplexity")


def classify(docs: DataFrame, labels: DataFrame, quantile: float = QUANTILE, slack: float = SLACK) -> DataFrame:
    """``(doc_id, r, lang, units, nats, threshold, variety, floor, keep)`` of every row of ``docs(doc_id, lang, text)``.

    Null and empty texts have no perplexity and are kept, and so is everything where no trusted text is held out. Null
    languages are one language. Rows that repeat a document score alike. An empty table gives an empty table.
    """
    scored = perplexities(docs.select("doc_id", "lang", "text"), labels)
    # A short text's mean strays farther from its language's: what it may stray falls with the root of its length.
    scored = scored.withColumn("fit", F.col("nats") - STRAY / F.sqrt(F.greatest("units", F.lit(1))))
    held = scored.where("held AND nats IS NOT NULL")
    high, low = F.percentile_approx("fit", quantile, 10000), F.percentile_approx("variety", 1 - quantile, 10000)
    of_all, low_of_all = held.agg(high, low).first()
    enough = F.count("*") >= LEAST_HELD
    by_lang = held.groupBy("lang").agg(F.when(enough, high).alias("own"), F.when(enough, low).alias("own_low")).withColumnRenamed("lang", "_lang")
    told = scored.join(by_lang, F.col("lang").eqNullSafe(F.col("_lang")), "left")
    threshold = F.coalesce("own", F.lit(of_all).cast("double")) + slack + STRAY / F.sqrt(F.greatest("units", F.lit(1)))
    floor = LEAST_VARIETY * F.coalesce("own_low", F.lit(low_of_all).cast("double"))
    keep = F.coalesce((F.col("nats") <= threshold) & (F.col("variety") >= floor), F.lit(True))
    return told.select(F.col("id").alias("doc_id"), "r", "lang", "units", "nats", threshold.alias("threshold"), "variety", floor.alias("floor"), keep.alias("keep"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = classify(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
    return found.select("doc_id", "lang", "units", F.exp("nats").alias("perplexity"), F.exp("threshold").alias("threshold"), "variety", F.col("floor").alias("variety_floor"), "keep")


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier keeps, those without an id included: a row is known by its id and its text."""
    rejected = classify(docs, read_table(spark, sf_dir, "labels")).where(~F.col("keep")).select(F.col("doc_id").alias("__reject_id"), F.col("r").alias("__reject_text"))
    return docs.join(rejected, F.col("doc_id").eqNullSafe(F.col("__reject_id")) & F.xxhash64("text").eqNullSafe(F.col("__reject_text")), "left_anti")
