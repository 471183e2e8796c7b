"""Incremental removal of repeated word windows over a log-structured fingerprint index.

Every window of ``window`` words falls to its anchor, the least hash of its ``gram``-word grams; equal windows have equal
anchors. Consecutive windows with one anchor form a segment. The index holds one narrow row per distinct segment, ``(a, s, s2,
d)``: its anchor, 128 bits of SHA-256 over its very words, and the least document that has it. Rows lie in immutable runs,
tables bucketed by anchor and sorted by it, so that a new batch's run is merge-joined with each older one, bucket by
bucket: an append exchanges no old run. Every few batches the runs are compacted into one. Segments of equal anchor and digest are equal window for window. Where an anchor has
several digests, the texts of the documents that own those segments are read again, and each window's own words are digested
and compared. So a match is never taken on the word of the rolling hashes that found it. Bitmaps of fixed size, of anchors and
of documents, thin the runs and tell the scans which texts and segments to look at; a join drops their false hits.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skewroute.llm.common import BITMAP_BITS, bit_set, bitmap_of, delete_path, discard, free_shuffles, in_bitmap, input_bytes, join_counted, materialize, portions, read_table, scratch_path, tidy, words_of

WINDOW = 50
GRAM = 25
FAN_IN = 4
#: Bytes of stored text whose segments share a bucket, and the most buckets that a run is cut into.
BUCKET_BYTES = 32 << 20
MOST_BUCKETS = 1 << 16
#: Batches that a whole table is fed in: more than ``FAN_IN``, so that runs are compacted on the way.
BATCHES = 6
_BASE = np.uint64(0x9E3779B97F4A7C15)


def _word_hashes(words: list[bytes]) -> np.ndarray:
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(w) for w in words), np.uint64, len(words))


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def _rolling(h: np.ndarray, width: int, base: np.uint64) -> np.ndarray:
    """Mixed polynomial hash of every run of ``width`` words."""
    n = len(h) - width + 1
    acc = np.zeros(n, np.uint64)
    for j in range(width):
        acc = acc * base + h[j : j + n]
    return _mix(acc)


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    span = 1
    while 2 * span <= width:
        x = np.minimum(x[:-span], x[span:])
        span *= 2
    rest = width - span
    return np.minimum(x[: len(x) - rest], x[rest:]) if rest else x


def segments(h: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First window, number of windows and anchor of each segment of a text's word hashes."""
    if len(h) < window:
        none = np.zeros(0, np.int64)
        return none, none, none.astype(np.uint64)
    least = _sliding_min(_rolling(h, gram, _BASE), window - gram + 1)
    first = np.flatnonzero(np.r_[True, least[1:] != least[:-1]])
    return first, np.diff(np.r_[first, len(least)]), least[first]


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Id, a hash that tells rows with one id apart, and the text; rows without an id take no part."""
    return docs.select(F.col(id_col).cast("long").alias("d"), F.xxhash64(text_col).alias("r"), F.col(text_col).alias("t")).where("d IS NOT NULL")


class _Words:
    """The words of a text laid out so that any run of them can be digested."""

    def __init__(self, words: list[bytes]):
        self.raw = b" ".join(words)
        self.at = np.cumsum([0, *(len(w) + 1 for w in words)])

    def digests(self, first: np.ndarray, count: np.ndarray | int) -> np.ndarray:
        """128 bits of SHA-256 over runs of words, as two longs each."""
        low, high, raw, sha = self.at[first].tolist(), (self.at[first + count] - 1).tolist(), self.raw, hashlib.sha256
        return np.frombuffer(b"".join([sha(raw[a:b]).digest()[:16] for a, b in zip(low, high, strict=True)]), "<i8").reshape(-1, 2)


def segment_rows(keyed: DataFrame, window: int, gram: int) -> DataFrame:
    """``(d, r, p, n, a, s, s2)`` of every segment of every text: ``n`` windows from word ``p`` on."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in portions(batches):
            parts = []
            for d, r, t in zip(*(b.column(c).to_pylist() for c in ("d", "r", "t")), strict=True):
                words = words_of(t)
                p, n, a = segments(_word_hashes(words), window, gram) if len(words) >= window else ((), (), None)
                if len(p):
                    s = _Words(words).digests(p, n + window - 1)
                    parts.append((np.full(len(p), d, np.int64), np.full(len(p), r, np.int64), p.astype(np.int32), n.astype(np.int32), a.view(np.int64), s[:, 0], s[:, 1]))
            if parts:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*parts, strict=True)], ["d", "r", "p", "n", "a", "s", "s2"])

    return keyed.mapInArrow(tidy(run), "d long, r long, p int, n int, a long, s long, s2 long")


def _window_rows(keyed: DataFrame, documents: Broadcast, anchors: Broadcast, window: int, gram: int) -> DataFrame:
    """``(a, s, s2, ws)``: the digests of the windows of segments whose anchor is in the one bitmap, in texts whose document is in the
    other, each segment once a batch. Other texts are passed over unread."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        owners, bits = documents.value, anchors.value
        for b in batches:
            found: dict[tuple[int, int, int], np.ndarray] = {}
            for part in portions([b]):
                for t in part.filter(pa.array(bit_set(owners, part.column("k").to_numpy().view(np.uint64)))).column("t").to_pylist():
                    words = words_of(t)
                    p, n, a = segments(_word_hashes(words), window, gram)
                    hit = np.flatnonzero(bit_set(bits, a)) if len(p) else ()
                    if not len(hit):
                        continue
                    laid = _Words(words)
                    for i, anchor, (s, s2) in zip(hit.tolist(), a[hit].view(np.int64).tolist(), laid.digests(p[hit], n[hit] + window - 1).tolist(), strict=True):
                        if (anchor, s, s2) not in found:
                            found[anchor, s, s2] = laid.digests(np.arange(p[i], p[i] + n[i]), window)
            if found:
                keys = np.array(list(found), np.int64)
                ends = np.cumsum([0, *map(len, found.values())]).astype(np.int32)
                flat = np.concatenate(list(found.values()))
                pairs = pa.StructArray.from_arrays([pa.array(flat[:, 0].copy()), pa.array(flat[:, 1].copy())], ["w", "w2"])
                yield pa.RecordBatch.from_arrays([*(pa.array(keys[:, k].copy()) for k in range(3)), pa.ListArray.from_arrays(pa.array(ends), pairs)], ["a", "s", "s2", "ws"])

    return keyed.select(F.xxhash64("d").alias("k"), "t").mapInArrow(tidy(run), "a long, s long, s2 long, ws array<struct<w: long, w2: long>>")


def _combined(own: DataFrame) -> DataFrame:
    """``(a, s, s2, low, high)``: distinct segments of each batch of rows, with the least and the last document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            each = pa.Table.from_batches([b]).group_by(["a", "s", "s2"]).aggregate([("d", "min"), ("d", "max")])
            yield from each.select(["a", "s", "s2", "d_min", "d_max"]).rename_columns(["a", "s", "s2", "low", "high"]).to_batches()

    return own.select("a", "s", "s2", "d").mapInArrow(tidy(run), "a long, s long, s2 long, low long, high long")


@dataclass
class WindowIndex:
    """Runs of segment rows in the shared folder. ``append`` takes batches in ascending order of document id.

    ``corpus`` must give the texts of all documents that were appended: windows are verified against it. Rows with a null id are
    not indexed and nothing in them is repeated.
    """

    spark: SparkSession
    corpus: DataFrame
    id_col: str = "doc_id"
    text_col: str = "text"
    window: int = WINDOW
    gram: int = GRAM
    fan_in: int = FAN_IN
    bitmap_bits: int = BITMAP_BITS
    #: Buckets of every run, fixed for the life of an index (None: by the bytes of the first corpus).
    buckets: int | None = None
    runs: list[str] = field(default_factory=list)
    paths: dict[str, str] = field(default_factory=dict)
    compactions: int = 0

    def __post_init__(self) -> None:
        self.buckets = self.buckets or min(MOST_BUCKETS, max(8, (input_bytes(self.corpus) or 0) // BUCKET_BYTES))

    def _write_run(self, rows: DataFrame) -> str:
        """An immutable run of ``(a, s, s2, d)``; rows come dealt by anchor, so each bucket is one sorted file."""
        table, path = f"skewroute_run_{uuid.uuid4().hex}", scratch_path(self.spark, "run")
        rows.write.format("parquet").bucketBy(self.buckets, "a").sortBy("a").option("path", path).saveAsTable(table)
        self.paths[table] = path
        return table

    def history(self) -> DataFrame | None:
        """All runs' rows, read as plain files: Spark takes a union of bucketed scans to be dealt by bucket, which it is not when it runs."""
        return self.spark.read.schema("a long, s long, s2 long, d long").parquet(*(self.paths[r] for r in self.runs)) if self.runs else None

    def _drop(self, tables: list[str]) -> None:
        for t in tables:
            self.spark.sql(f"DROP TABLE IF EXISTS {t}")
            delete_path(self.spark, self.paths.pop(t))

    def compact(self) -> None:
        """Merge all runs into one; of a segment the least document stays. The old runs go when the new one is there."""
        if len(self.runs) > 1:
            old = self.runs
            self.runs = [self._write_run(self.history().repartition(self.buckets, "a").groupBy("a", "s", "s2").agg(F.min("d").alias("d")))]
            self._drop(old)
            self.compactions += 1

    def close(self) -> None:
        """Drop the runs."""
        self._drop(self.runs)
        self.runs = []

    def _anchors_of(self, run: str) -> DataFrame:
        """One row an anchor of a run, where its bucket lies."""
        ends = (f(c).alias(f.__name__ + c) for c in ("d", "s", "s2") for f in (F.min, F.max))
        return self.spark.table(run).groupBy("a").agg(F.count("*").alias("c"), *ends)

    def _shared_anchors(self) -> DataFrame:
        """``(a, c, several)`` of the newest run's anchors that two documents have, with their number of rows in all runs.

        The newest run is merge-joined with each older one, bucket by bucket: no run is exchanged.
        """
        own = self._anchors_of(self.runs[-1])
        for run in self.runs[:-1]:
            old = self._anchors_of(run).select("a", *(F.col(c).alias(f"o_{c}") for c in own.columns[1:]))
            both = own.join(old.hint("merge"), "a", "left")
            low, high = (lambda c: F.least(c, f"o_{c}").alias(c)), (lambda c: F.greatest(c, f"o_{c}").alias(c))
            own = both.select("a", (F.col("c") + F.coalesce("o_c", F.lit(0))).alias("c"), *((low if c.startswith("min") else high)(c) for c in own.columns[2:]))
        return own.where("maxd > mind").selectExpr("a", "c", "mins < maxs OR mins2 < maxs2 AS several")

    def append(self, batch: DataFrame) -> DataFrame:
        """Index a batch and give its repeated windows: ``(d, r, p, n)``, ``n`` windows from word ``p`` on.

        A window is repeated if its words start in a document with a smaller id, of this batch or of an earlier one.
        """
        key = ["a", "s", "s2"]
        own = materialize(segment_rows(_keyed(batch, self.id_col, self.text_col), self.window, self.gram), "segments")
        # Copies meet where they were scanned; of a distinct segment a row is kept, and one more where documents differ.
        ends = _combined(own).repartition(self.buckets, "a").groupBy(*key).agg(F.min("low").alias("low"), F.max("high").alias("high"))
        self.runs.append(self._write_run(ends.select(*key, F.explode(F.array_distinct(F.array("low", "high"))).alias("d"))))

        # Anchors of the new batch that two documents share; those that it lacks were settled before.
        anchors = materialize(self._shared_anchors(), "anchors")
        rows, bits = anchors.agg(F.sum("c")).first()[0] or 0, bitmap_of(anchors, self.bitmap_bits)
        mine = materialize(in_bitmap(own, bits), "mine")
        counted = materialize(mine.groupBy(*key).agg(F.count("*").alias("c")), "counted")
        common = join_counted(in_bitmap(self.history(), bits), anchors, ["a"], rows)
        held = common.groupBy(*key).agg(F.min("d").alias("d0"), F.first("several").alias("several"))
        shared = materialize(held.join(counted, key, "left").fillna(0, ["c"]), "shared")

        early = self._early_windows(shared.where("several").select(*key, "d0"), key)
        told = join_counted(mine, shared, key, mine.count())
        whole = told.where("d > d0").select("d", "r", "p", "n")
        # Segments that start here may still hold windows that smaller documents have elsewhere.
        partial = told.where("several AND d = d0").join(early, key).select("d", "r", "p", F.explode("js").alias("j"))
        found = materialize(whole.unionByName(partial.select("d", "r", (F.col("p") + F.col("j")).alias("p"), F.lit(1).alias("n"))), "repeated")
        discard(own, anchors, mine, counted, shared, early)
        bits.destroy()
        if len(self.runs) >= self.fan_in:
            self.compact()
        return found

    def _early_windows(self, several: DataFrame, key: list[str]) -> DataFrame:
        """``(a, s, s2, js)``: which windows of the segments ``(a, s, s2, d0)`` a smaller document has in another segment."""
        texts = _keyed(self.corpus, self.id_col, self.text_col)
        owners, anchors = bitmap_of(several.select(F.xxhash64("d0").alias("k")), self.bitmap_bits, "k"), bitmap_of(several, self.bitmap_bits)
        hashed = _window_rows(texts, owners, anchors, self.window, self.gram)
        arrays = materialize(several.join(hashed.groupBy(*key).agg(F.first("ws").alias("ws")), key), "windows")
        at = ["a", "w", "w2"]
        each = arrays.select(*key, "d0", F.posexplode("ws").alias("j", "x")).select(*key, "d0", "j", "x.w", "x.w2")
        least = materialize(each.groupBy(*at).agg(F.min("d0").alias("m"), F.max("d0").alias("top"), F.count("*").alias("c")).where("m < top").drop("top"), "least")
        total = arrays.agg(F.sum(F.size("ws"))).first()[0] or 0
        early = materialize(join_counted(each, least, at, total).where("m < d0").groupBy(*key).agg(F.collect_list("j").alias("js")), "early")
        discard(arrays, least)
        for bits in (owners, anchors):
            bits.destroy()
        return early


def remove_repeats(docs: DataFrame, repeated: DataFrame, id_col: str, text_col: str, window: int, keep: list[str], digest: bool, bitmap_bits: int = BITMAP_BITS) -> DataFrame:
    """Join the repeated windows to their documents and drop the words they cover.

    ``row`` holds the columns ``keep`` of the input, beside ``n_words``, ``n_removed`` and ``kept_sha256`` (digest) or the
    kept words joined by a space as ``kept`` (null where nothing was removed). Only texts that may have such windows, by a
    bitmap of their ids, are dealt out to meet them; the others are settled where they are scanned.
    """
    spans = materialize(repeated.groupBy("d", "r").agg(F.collect_set(F.struct("p", "n")).alias("_spans")), "spans")
    bitmap = bitmap_of(spans.select(F.xxhash64("d").alias("k")), bitmap_bits, "k")
    keyed = docs.select(F.struct(*keep).alias("row"), F.col(id_col).cast("long").alias("_d"), F.xxhash64(text_col).alias("_r"), F.col(text_col).alias("_t"), F.xxhash64(F.col(id_col).cast("long")).alias("_k"))
    touched = in_bitmap(keyed, bitmap, "_k").join(spans.select(F.col("d").alias("_d"), F.col("r").alias("_r"), "_spans"), ["_d", "_r"], "left").select("row", "_t", "_spans")
    last = "kept_sha256" if digest else "kept"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in portions(batches):
            total, removed, kept = [], [], []
            each = b.column("_spans").to_pylist() if "_spans" in b.schema.names else [None] * b.num_rows
            for t, spans in zip(b.column("_t").to_pylist(), each, strict=True):
                words, gone = words_of(t), 0
                if spans:
                    edge = np.zeros(len(words) + 1, np.int64)
                    at = np.array([(x["p"], x["n"]) for x in spans], np.int64)
                    np.add.at(edge, at[:, 0], 1)
                    np.add.at(edge, at[:, 0] + at[:, 1] + window - 1, -1)
                    stay = np.cumsum(edge[:-1]) == 0
                    gone = len(words) - int(stay.sum())
                total.append(len(words))
                removed.append(gone)
                if gone:
                    words = [w for w, s in zip(words, stay.tolist(), strict=True) if s]
                if digest:
                    kept.append(hashlib.sha256(b" ".join(words)).hexdigest())
                else:
                    kept.append(b" ".join(words).decode("utf-8", "replace") if gone else None)
            yield pa.RecordBatch.from_arrays([b.column("row"), pa.array(total, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.string())], ["row", "n_words", "n_removed", last])

    def untouched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Passed over and settled by one worker: a filter of its own would hold the texts in a second one beside it.
        yield from run(b.filter(pa.array(~bit_set(bitmap.value, b.column("_k").to_numpy().view(np.uint64)))) for b in portions(batches))

    schema = T.StructType([keyed.schema["row"], T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField(last, T.StringType())])
    return keyed.select("row", "_t", "_k").mapInArrow(tidy(untouched), schema).unionByName(touched.mapInArrow(tidy(run), schema))


def repeated_windows(docs: DataFrame, batches: int = BATCHES, window: int = WINDOW, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Feed a whole table to a fresh index in ``batches`` ascending id ranges; all repeated windows."""
    spark, key = docs.sparkSession, F.col(id_col).cast("long")
    cuts = docs.agg(F.percentile_approx(key, [(i + 1) / batches for i in range(batches - 1)], 1000)).first()[0] if batches > 1 else None
    cuts = sorted(set(cuts or []))
    index, out = WindowIndex(spark, docs, id_col, text_col, window, gram), None  # buckets for the whole table
    for low, high in zip([None, *cuts], [*cuts, None], strict=True):
        index.corpus = docs if high is None else docs.where(key <= high)
        found = index.append(index.corpus if low is None else index.corpus.where(key > low))
        out = found if out is None else out.unionByName(found)
        free_shuffles(spark)
    index.close()
    return out


def op7_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    out = remove_repeats(docs, repeated_windows(docs), "doc_id", "text", WINDOW, ["doc_id"], digest=True)
    return out.select("row.doc_id", "n_words", "n_removed", "kept_sha256")


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without their repeated windows; documents left without a word go. ``n_chars`` follows the text."""
    names = docs.columns
    cut = remove_repeats(docs, repeated_windows(docs), "doc_id", "text", WINDOW, names, digest=False).where("n_removed = 0 OR n_removed < n_words")
    new = {"text": F.coalesce("kept", "row.text")}
    if "n_chars" in names:
        new["n_chars"] = F.when(F.col("n_removed") > 0, F.length("kept").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("row.n_chars"))
    return cut.select(*(new.get(c, F.col("row").getField(c)).alias(c) for c in names))
