"""Vector best-fit packing of token pieces into sequences.

A piece's demand on a sequence (tokens, one document, attention cost) depends on its length alone, so the packing
problem is the histogram of lengths: at most ``capacity`` rows whatever the corpus. Bins are filled on that histogram
in bulk (bins with equal residuals are one class with a multiplicity), then every piece finds its place by its rank
among the pieces of its length. Ranks come from counts per (length, shard) and their running sums, so a length that a
third of the pieces share is spread over all shards.
"""

from __future__ import annotations

import functools
import json
import sys
import zlib
from array import array
from bisect import bisect_left
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skewroute.llm.common import input_partitions, materialize, read_table, tidy, words_of

CAPACITY = 4096
END_ID = 1
TOKENIZER = "word_bpe_49k.json"
#: Bytes of words, pieces and ids that a worker remembers, with what Python adds to each; beyond it starts anew.
_MEMO_BYTES = 96 << 20
_ENTRY_BYTES = 250


@dataclass(frozen=True)
class Capacities:
    """What one sequence may hold. Attention cost of a piece is its length squared."""

    tokens: int = CAPACITY
    documents: int = CAPACITY
    attention: int = CAPACITY * CAPACITY

    def demand(self, length: int) -> tuple[int, int, int]:
        return length, 1, length * length

    @property
    def all(self) -> tuple[int, int, int]:
        return self.tokens, self.documents, self.attention


def _score(rule: str, weights: tuple[float, ...], caps: tuple[int, ...], left: tuple[int, ...], need: tuple[int, ...]) -> float:
    """Lower is better: weighted residual norm after placing, or minus the weighted dot product of need and room."""
    if rule == "norm":
        return sum(w * ((r - d) / c) ** 2 for w, r, d, c in zip(weights, left, need, caps, strict=True))
    return -sum(w * (d / c) * (r / c) for w, r, d, c in zip(weights, left, need, caps, strict=True))


def plan_bins(histogram: dict[int, int], caps: Capacities, rule: str = "norm", weights: tuple[float, float, float] = (1.0, 1e-3, 1e-3)) -> list[tuple[int, tuple[tuple[int, int], ...]]]:
    """``[(how many bins, ((length, pieces of it in each), ...)), ...]``, longest pieces first in each bin.

    Best-fit decreasing on the histogram: classes of open bins with equal residuals, best class by ``rule`` ("norm" or
    "dot"); as many equal pieces as fit go into a bin at once, which is what best-fit does one by one.
    """
    full, classes, contents = caps.all, defaultdict(list), {}
    order: list[int] = []  # token residuals with open classes, ascending
    out: list[tuple[int, tuple]] = []

    def put(left: tuple[int, ...], count: int, has: tuple) -> None:
        if left[0] == 0 or left[1] == 0 or left[2] == 0:
            out.append((count, has))
            return
        if left[0] not in contents:
            contents[left[0]] = True
            order.insert(bisect_left(order, left[0]), left[0])
        classes[left[0]].append((left, count, has))

    def best(need: tuple[int, ...]):
        found, at = None, None
        # Under "norm" the token residual dominates: the scan stops once no wider class can score lower.
        for tokens in order[bisect_left(order, need[0]) :]:
            if found is not None and rule == "norm" and weights[0] * ((tokens - need[0]) / full[0]) ** 2 > found:
                break
            for k, (left, _, _) in enumerate(classes[tokens]):
                if all(r >= d for r, d in zip(left, need, strict=True)) and (found is None or (s := _score(rule, weights, full, left, need)) < found):
                    found, at = _score(rule, weights, full, left, need), (tokens, k)
        return at

    for length in sorted(histogram, reverse=True):
        need, todo = caps.demand(length), histogram[length]
        if any(d > c for d, c in zip(need, full, strict=True)):
            raise ValueError(f"a piece of {length} tokens exceeds the capacities of a sequence")
        while todo:
            at = best(need)
            if at is None:
                left, count, has = full, None, ()
            else:
                left, count, has = classes[at[0]].pop(at[1])
                if not classes[at[0]]:
                    del classes[at[0]], contents[at[0]]
                    order.pop(bisect_left(order, at[0]))
            fits = min(r // d for r, d in zip(left, need, strict=True))
            take = min(fits, todo)
            bins = todo // take if count is None else min(count, todo // take)
            if count is not None and bins < count:
                put(left, count - bins, has)
            put(tuple(r - take * d for r, d in zip(left, need, strict=True)), bins, (*has, (length, take)))
            todo -= bins * take
    for tokens in order:
        out += [(count, has) for _, count, has in classes[tokens]]
    return out


def _slots(plan: list[tuple[int, tuple[tuple[int, int], ...]]]) -> dict[int, tuple[np.ndarray, ...]]:
    """Per length: first rank, first sequence id, pieces in each bin, offset of the first of them, of every plan row."""
    rows, used, sequence = defaultdict(list), defaultdict(int), 0
    for bins, has in plan:
        offset = 0
        for length, each in has:
            rows[length].append((used[length], sequence, each, offset))
            used[length] += bins * each
            offset += length * each
        sequence += bins
    return {length: tuple(np.array(c, np.int64) for c in zip(*r, strict=True)) for length, r in rows.items()}


# Fixed values of the tokenizer: its pieces, and the printable stand-ins of bytes that byte-level BPE works on.
_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
_PIECES = regex.compile(_SPLIT)
_NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]}
_PRE_TOKENIZER = {"type": "Sequence", "pretokenizers": [{"type": "Split", "pattern": {"Regex": _SPLIT}, "behavior": "Removed", "invert": True}, {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}]}
_PLAIN = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
_STAND_IN = {b: chr(b) for b in _PLAIN} | {b: chr(0x100 + i) for i, b in enumerate(b for b in range(256) if b not in set(_PLAIN))}


def _little(ids: array) -> bytes:
    """Bytes of 32-bit ids, little-endian on any machine."""
    if sys.byteorder == "big":
        ids.byteswap()
    return ids.tobytes()


@functools.cache
def _tokenizer(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@functools.cache
def _splits_as_here(path: str) -> bool:
    """Whether a tokenizer prepares and splits text as ``WordTokens`` does; one that does not is given whole texts."""
    told = json.loads(Path(path).read_text(encoding="utf-8"))
    special = all("<|" in t["content"] for t in told.get("added_tokens", []))
    return special and told.get("normalizer") == _NORMALIZER and told.get("pre_tokenizer") == _PRE_TOKENIZER and told["model"].get("type") == "BPE"


class WordTokens:
    """Ids of whole texts through a bounded memo of words; exact because the tokenizer never joins over white space.

    That holds for tokenizers that split as the fixed values above say (``_splits_as_here``); with any other one, every text
    goes through the whole tokenizer.

    A new word of Latin letters is split into the tokenizer's pieces here and each new piece goes to its BPE model; any
    other word, and one that may hold a special token, goes through the whole tokenizer.
    """

    def __init__(self, path: str):
        self.tokenizer = _tokenizer(path)
        self.model = self.tokenizer.model
        self.plain = _splits_as_here(path)
        self.memo: dict[bytes, bytes] = {}
        self.pieces: dict[str, bytes] = {}
        self.held = 0
        self.byte_map = str.maketrans({chr(b): c for b, c in _STAND_IN.items()})

    def _piece(self, piece: str) -> bytes:
        tokens = self.model.tokenize(piece.encode().decode("latin-1").translate(self.byte_map))
        self.pieces[piece] = out = _little(array("I", [t.id for t in tokens]))
        self.held += 4 * len(piece) + _ENTRY_BYTES
        return out

    def _whole(self, text: str) -> bytes:
        return _little(array("I", self.tokenizer.encode(text, add_special_tokens=False).ids))

    def learn(self, words: set[bytes]) -> None:
        new = words.difference(self.memo)
        if self.held > _MEMO_BYTES:
            self.memo.clear()
            self.pieces.clear()
            self.held, new = 0, words
        if not new:
            return
        # Words hold no line feed, so all new ones are decoded and lower-cased in one go.
        joined = b"\n".join(new).decode("utf-8", "replace")
        self.held += 2 * len(joined) + _ENTRY_BYTES * len(new)
        memo, known, piece = self.memo, self.pieces.get, self._piece
        for word, text, low in zip(new, joined.split("\n"), joined.lower().split("\n"), strict=True):
            if "<|" in text or not text.isascii() and max(text) >= "\u0250":
                memo[word] = self._whole(text)
            elif low.isalpha():
                memo[word] = known(low) or piece(low)
            elif low[-1] in ".,;:!?" and low[:-1].isalpha():
                stem, mark = low[:-1], low[-1]
                memo[word] = (known(stem) or piece(stem)) + (known(mark) or piece(mark))
            else:
                memo[word] = b"".join([known(p) or piece(p) for p in _PIECES.findall(low)])

    def ids(self, texts: list[str]) -> Iterator[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        if not self.plain:
            yield from (self._whole(t) for t in texts)
            return
        step = 256
        for i in range(0, len(texts), step):
            split = [words_of(t) for t in texts[i : i + step]]
            self.learn(set().union(*split))
            get = self.memo.__getitem__
            yield from (b"".join(map(get, words)) for words in split)


def pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(row_id, doc_id, piece, start, length, ids_crc32)``: each text's ids and the end id, cut at ``capacity``."""
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = WordTokens(tokenizer_path)
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
        for b in batches:
            rows = []
            for doc, key, ids in zip(b.column("i").to_pylist(), b.column("r").to_pylist(), tokens.ids(b.column("t").to_pylist()), strict=True):
                ids += end
                for n, at in enumerate(range(0, len(ids), 4 * capacity)):
                    cut = ids[at : at + 4 * capacity]
                    rows.append((key, doc, n, at // 4, len(cut) // 4, zlib.crc32(cut)))
            columns = zip(*rows, strict=True) if rows else [()] * len(kinds)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["row_id", "doc_id", "piece", "start", "length", "ids_crc32"])

    source = docs.select(F.col(id_col).cast("long").alias("i"), F.xxhash64(F.col(id_col), F.col(text_col)).alias("r"), F.coalesce(F.col(text_col), F.lit("")).alias("t"))
    return source.mapInArrow(tidy(run), "row_id long, doc_id long, piece int, start long, length long, ids_crc32 long")


def place(cut: DataFrame, caps: Capacities | None = None, rule: str = "norm") -> DataFrame:
    """Add ``sequence_id`` and ``offset`` to materialised pieces (``row_id, piece, length`` and others are kept).

    The driver takes the histogram of lengths, at most ``capacity`` rows, and sends back as many placing rows as the
    plan has. Ranks within a length: pieces are dealt by (length, shard), each shard's running sum is its first rank.
    """
    caps = caps or Capacities()
    spark, shards = cut.sparkSession, max(8, 2 * input_partitions(cut))
    dealt = cut.withColumn("_shard", F.pmod(F.xxhash64("row_id", "piece"), F.lit(shards)).cast("int"))
    histogram = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect()}
    slots = spark.sparkContext.broadcast(_slots(plan_bins(histogram, caps, rule)))
    counts = dealt.groupBy("length", "_shard").agg(F.count("*").alias("_n"))
    first = counts.selectExpr("length", "_shard", "sum(_n) OVER (PARTITION BY length ORDER BY _shard) - _n AS _first")
    ranked = dealt.selectExpr("*", "row_number() OVER (PARTITION BY length, _shard ORDER BY row_id, piece) - 1 AS _in_shard").join(first, ["length", "_shard"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lengths, rank = b.column("length").to_numpy(), b.column("_rank").to_numpy()
            sequence, offset = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
            for length in np.unique(lengths):
                own = np.flatnonzero(lengths == length)
                start, seq, each, off = slots.value[length]
                at = np.searchsorted(start, rank[own], side="right") - 1
                k = rank[own] - start[at]
                sequence[own], offset[own] = seq[at] + k // each[at], off[at] + k % each[at] * length
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in kept), pa.array(sequence), pa.array(offset)], [*kept, "sequence_id", "offset"])

    kept = cut.columns
    ranked = ranked.select(*cut.columns, (F.col("_first") + F.col("_in_shard")).alias("_rank"))
    schema = T.StructType([*cut.schema.fields, T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])
    return ranked.mapInArrow(run, schema)


def pack(docs: DataFrame, tokenizer_path: str, caps: Capacities | None = None, rule: str = "norm", end_id: int = END_ID) -> DataFrame:
    """One row per piece: ``row_id, doc_id, piece, start, length, ids_crc32, sequence_id, offset``.

    Null and empty texts are one piece, the end id alone. Rows that repeat a document are packed as often as they
    occur. An empty table gives an empty table. Only the id and text columns are read.
    """
    caps = caps or Capacities()
    return place(materialize(pieces(docs, tokenizer_path, caps.tokens, end_id), "pieces"), caps, rule)


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    packed = pack(read_table(spark, sf_dir, "documents"), tokenizer_path())
    return packed.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(docs, tokenizer_path()).drop("row_id")
