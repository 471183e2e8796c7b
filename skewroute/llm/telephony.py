"""Telephony audio columns: G.711 mu-law and A-law by lookup tables, IMA ADPCM blocks by numpy across blocks, PCM.

Samples live in WAVE containers (format 7 mu-law, 6 A-law, 17 IMA ADPCM, 1 PCM). Companded bytes are kept as they are, so a
mu-law or A-law payload is stored without loss; PCM is what decoding and resampling give. Both are written as columns of Zstandard
Parquet and read back before anything is told about them.
"""

from __future__ import annotations

import hashlib
import math
import struct
import zlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skewroute.llm.common import discard, materialize, read_table, scratch_path, tidy

PCM, ALAW, MULAW, IMA = 1, 6, 7, 17
RATE = 8000
FRAME = 576


def _mulaw_table() -> np.ndarray:
    """Expansion of the 256 mu-law bytes: inverted bits, 3-bit segment, 4-bit step, bias 132 on 16 bits."""
    b = ~np.arange(256, dtype=np.int32) & 0xFF
    size = ((((b & 15) << 3) + 132) << (b >> 4 & 7)) - 132
    return np.where(b & 0x80, -size, size).astype(np.int16)


def _alaw_table() -> np.ndarray:
    """Expansion of the 256 A-law bytes: even bits inverted, 3-bit segment, 4-bit step."""
    b = np.arange(256, dtype=np.int32) ^ 0x55
    segment, step = b >> 4 & 7, (b & 15) << 4
    size = np.where(segment == 0, step + 8, (step + 264) << np.maximum(segment - 1, 0))
    return np.where(b & 0x80, size, -size).astype(np.int16)


MULAW_PCM, ALAW_PCM = _mulaw_table(), _alaw_table()

# Fixed values of the IMA ADPCM format: quantizer steps and index moves.
IMA_STEPS = np.array(
    [7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767],
    np.int32,
)
IMA_MOVES = np.array([-1, -1, -1, -1, 2, 4, 6, 8] * 2, np.int32)


def expand(payload: bytes, law: int) -> np.ndarray:
    """16-bit PCM of companded bytes."""
    return (MULAW_PCM if law == MULAW else ALAW_PCM)[np.frombuffer(payload, np.uint8)]


def compress(pcm: np.ndarray, law: int) -> bytes:
    """The companded byte nearest to each sample (smaller byte on ties)."""
    table = (MULAW_PCM if law == MULAW else ALAW_PCM).astype(np.int32)
    order = np.argsort(table, kind="stable")
    levels = table[order]
    at = np.clip(np.searchsorted(levels, pcm), 1, 255)
    low = np.abs(pcm - levels[at - 1]) <= np.abs(levels[at] - pcm)
    return order[np.where(low, at - 1, at)].astype(np.uint8).tobytes()


def _ima_step(nibble: np.ndarray, value: np.ndarray, index: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    step = IMA_STEPS[index]
    diff = (step >> 3) + np.where(nibble & 4, step, 0) + np.where(nibble & 2, step >> 1, 0) + np.where(nibble & 1, step >> 2, 0)
    return np.clip(value + np.where(nibble & 8, -diff, diff), -32768, 32767), np.clip(index + IMA_MOVES[nibble], 0, 88)


def ima_decode(data: bytes, block_align: int) -> np.ndarray:
    """PCM of mono IMA ADPCM blocks: one step of all blocks at a time, so the loop is as long as one block."""
    blocks = np.frombuffer(data[: len(data) // block_align * block_align], np.uint8).reshape(-1, block_align)
    value = blocks[:, :2].copy().view("<i2")[:, 0].astype(np.int32)
    index = np.minimum(blocks[:, 2], 88).astype(np.int32)
    out = np.empty((len(blocks), 1 + 2 * (block_align - 4)), np.int16)
    out[:, 0] = value
    for i in range(block_align - 4):
        byte = blocks[:, 4 + i].astype(np.int32)
        for half, nibble in enumerate((byte & 15, byte >> 4)):
            value, index = _ima_step(nibble, value, index)
            out[:, 1 + 2 * i + half] = value
    return out.ravel()


def ima_encode(pcm: np.ndarray, block_align: int = 256) -> bytes:
    """Mono IMA ADPCM blocks; the last block repeats the last sample to its end."""
    each = 1 + 2 * (block_align - 4)
    pad = -len(pcm) % each
    x = np.r_[pcm, np.full(pad, pcm[-1] if len(pcm) else 0, np.int16)].astype(np.int32).reshape(-1, each)
    out = np.zeros((len(x), block_align), np.uint8)
    out[:, :2] = x[:, 0].astype("<i2").view(np.uint8).reshape(-1, 2)
    value, index = x[:, 0].copy(), np.zeros(len(x), np.int32)
    for i in range(1, each):
        gap, step = x[:, i] - value, IMA_STEPS[index]
        size, nibble = np.abs(gap), np.where(gap < 0, 8, 0)
        for bit, part in ((4, step), (2, step >> 1), (1, step >> 2)):
            over = size >= part
            nibble, size = nibble | np.where(over, bit, 0), np.where(over, size - part, size)
        value, index = _ima_step(nibble, value, index)
        out[:, 4 + (i - 1) // 2] |= (nibble << (4 * ((i - 1) % 2))).astype(np.uint8)
    return out.tobytes()


def wave(payload: bytes, form: int, rate: int = RATE, bits: int = 8, block_align: int = 1) -> bytes:
    """A mono WAVE file around sample data; odd data gets the pad byte that the container asks for."""
    each = rate * block_align // (1 + 2 * (block_align - 4)) if form == IMA else rate * bits // 8
    fmt = struct.pack("<HHIIHH", form, 1, rate, each, block_align, bits) + (b"" if form == PCM else struct.pack("<HH", 2, 1 + 2 * (block_align - 4)) if form == IMA else b"\0\0")
    fact = b"" if form == PCM else b"fact" + struct.pack("<II", 4, len(payload) * 8 // bits)
    body = b"WAVEfmt " + struct.pack("<I", len(fmt)) + fmt + fact + b"data" + struct.pack("<I", len(payload)) + payload + b"\0" * (len(payload) % 2)
    return b"RIFF" + struct.pack("<I", len(body)) + body


def unwave(file: bytes) -> tuple[int, int, int, bytes]:
    """Format, rate, block align and sample data of a WAVE file."""
    if file[:4] != b"RIFF" or file[8:12] != b"WAVE":
        raise ValueError("not a WAVE file")
    at, form, rate, align = 12, 0, 0, 0
    while at + 8 <= len(file):
        name, (n,) = file[at : at + 4], struct.unpack_from("<I", file, at + 4)
        if name == b"fmt ":
            form, _, rate, _, align, _ = struct.unpack_from("<HHIIHH", file, at + 8)
        elif name == b"data":
            return form, rate, align, file[at + 8 : at + 8 + n]
        at += 8 + n + n % 2
    raise ValueError("no sample data")


def decode(file: bytes) -> tuple[int, np.ndarray]:
    """Rate and 16-bit PCM of a stored file of any of the four formats."""
    form, rate, align, data = unwave(file)
    if form in (MULAW, ALAW):
        return rate, expand(data, form)
    return rate, ima_decode(data, align) if form == IMA else np.frombuffer(data, "<i2")


def resample(pcm: np.ndarray, rate: int, to: int) -> np.ndarray:
    """Linear resampling to ``to`` Hz in exact integer positions, rounded half up."""
    if rate == to or not len(pcm):
        return pcm
    n = -(-len(pcm) * to // rate)
    at = np.arange(n, dtype=np.int64) * rate
    i, part = at // to, at % to
    x = pcm.astype(np.int64)
    nxt = x[np.minimum(i + 1, len(x) - 1)]
    return ((2 * (x[i] * (to - part) + nxt * part) + to) // (2 * to)).astype(np.int16)


def band_limited(pcm: np.ndarray, rate: int, to: int, half: int = 16) -> np.ndarray:
    """Resampling by a windowed sinc of ``half`` zero crossings a side, cut off at the lower of the two Nyquist rates.

    One row of 15-bit coefficients for each of the positions that outputs take between two inputs; sums are integers.
    """
    if rate == to or not len(pcm):
        return pcm
    common = math.gcd(rate, to)
    up, down, cut = to // common, rate // common, min(1.0, to / rate)
    reach = math.ceil(half / cut)
    offset = np.arange(1 - reach, reach + 1)
    away = offset[None, :] - np.arange(up)[:, None] / up
    weight = np.sinc(away * cut) * np.where(np.abs(away) <= reach, 0.5 + 0.5 * np.cos(np.pi * away / reach), 0)
    taps = np.rint(weight / weight.sum(axis=1, keepdims=True) * 32768).astype(np.int64)
    n = -(-len(pcm) * up // down)
    out, x = np.empty(n, np.int16), np.pad(pcm.astype(np.int64), reach, mode="edge")
    for lo in range(0, n, 1 << 14):
        at = np.arange(lo, min(n, lo + (1 << 14)), dtype=np.int64) * down
        sums = (x[(at // up)[:, None] + offset[None, :] + reach] * taps[at % up]).sum(axis=1)
        out[lo : lo + len(at)] = np.clip((sums + 16384) >> 15, -32768, 32767)
    return out


def pcm_features(pcm: np.ndarray, rate: int) -> str:
    """Duration, level, peak, zero crossings and the loudest frame, in integers so that they never differ by platform."""
    x = pcm.astype(np.int64)
    frames = (x[: len(x) // FRAME * FRAME].reshape(-1, FRAME) ** 2).sum(axis=1) if len(x) >= FRAME else np.array([(x**2).sum()])
    crossings = int(((x[1:] < 0) != (x[:-1] < 0)).sum()) if len(x) else 0
    mean = int((x**2).sum()) // max(1, len(x))
    return f"rate={rate};samples={len(x)};mean_square={mean};peak={int(np.abs(x).max(initial=0))};crossings={crossings};loudest={int(frames.argmax())};crc={zlib.crc32(pcm.astype('<i2').tobytes())}"


def pad(text: str | None, unit: int = FRAME) -> tuple[int, bytes]:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return len(raw), raw + b"\xff" * (max(unit, -(-len(raw) // unit) * unit) - len(raw))


#: Bytes of media that a Python worker holds at a time.
_STEP_BYTES = 8 << 20
_ZSTD = {"compression": "zstd", "parquet.page.size": str(8 << 20)}
#: Parts that a whole table is stored and read back in, so that the files of one part alone take room at a time.
PARTS = 4


def _law(payload: bytes) -> int:
    """Which of the two laws a payload goes under where none is named: by its own bits, so that equal texts agree."""
    return ALAW if zlib.crc32(payload) & 1 else MULAW


def _slices(b: pa.RecordBatch, column: str, limit: int = _STEP_BYTES) -> Iterator[pa.RecordBatch]:
    """A batch in parts of at most ``limit`` bytes of a column (one row at least)."""
    sizes = np.array([0 if not v.is_valid else v.as_buffer().size for v in b.column(column)], np.int64)
    at = np.cumsum(sizes) // limit
    cuts = [0, *(np.flatnonzero(at[1:] != at[:-1]) + 1).tolist(), b.num_rows]
    yield from (b.slice(lo, hi - lo) for lo, hi in zip(cuts, cuts[1:], strict=False) if hi > lo)


def written(media: DataFrame, name: str) -> DataFrame:
    """Store media columns and read them back."""
    path = scratch_path(media.sparkSession, name)
    media.write.options(**_ZSTD).parquet(path)
    out = media.sparkSession.read.schema(media.schema).parquet(path)
    out._scratch_path = path
    return out


def store(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", law: int | None = None, rate: int = RATE) -> DataFrame:
    """``(doc_id, n_bytes, media)``: texts as companded samples in a WAVE file; null and empty texts are one frame.

    ``law``: mu-law, A-law, or None for either of them by the payload.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            padded = [pad(t) for t in b.column("t").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("i"), pa.array([n for n, _ in padded], pa.int64()), pa.array([wave(p, law or _law(p), rate) for _, p in padded], pa.binary())], ["doc_id", "n_bytes", "media"])

    return docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")).mapInArrow(tidy(run), "doc_id long, n_bytes long, media binary")


def resampled(media: DataFrame, to: int, media_col: str = "media", sinc: bool = False) -> DataFrame:
    """Add ``pcm``: a 16-bit PCM WAVE file at ``to`` Hz of each stored file (null: null), by lines or (``sinc``) band-limited."""
    change = band_limited if sinc else resample

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (part for whole in batches for part in _slices(whole, media_col)):
            out = []
            for f in b.column(media_col).to_pylist():
                rate, pcm = decode(f) if f is not None else (to, None)
                out.append(None if pcm is None else wave(change(pcm, rate, to).astype("<i2").tobytes(), PCM, to, 16, 2))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.binary())], [*b.schema.names, "pcm"])

    return media.mapInArrow(tidy(run), T.StructType([*media.schema.fields, T.StructField("pcm", T.BinaryType())]))


_TOLD = ["payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256"]


def described(media: DataFrame) -> DataFrame:
    """Digests of the payload as read from stored files, and of the files, in place of ``media`` (null: null); other columns stay."""
    kinds, rest = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string()), [c for c in media.columns if c != "media"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (part for whole in batches for part in _slices(whole, "media")):
            rows = []
            for f in b.column("media").to_pylist():
                data = None if f is None else unwave(f)[3]
                rows.append((None,) * 5 if f is None else (len(data), hashlib.sha256(data).hexdigest(), zlib.crc32(data[-32:]), len(f), hashlib.sha256(f).hexdigest()))
            columns = zip(*rows, strict=True) if rows else [()] * 5
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in rest), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], [*rest, *_TOLD])

    kept = T.StructType([f for f in media.schema.fields if f.name != "media"])
    return media.mapInArrow(tidy(run), T.StructType([*kept.fields, *T._parse_datatype_string("payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string").fields]))


def featured(pcm: DataFrame) -> DataFrame:
    """``feature`` of stored PCM files, in place of ``pcm`` (null: null); other columns stay."""
    rest = [c for c in pcm.columns if c != "pcm"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (part for whole in batches for part in _slices(whole, "pcm")):
            found = []
            for f in b.column("pcm").to_pylist():
                rate, x = decode(f) if f is not None else (0, None)
                found.append(None if x is None else pcm_features(x, rate))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in rest), pa.array(found, pa.string())], [*rest, "feature"])

    kept = [f for f in pcm.schema.fields if f.name != "pcm"]
    return pcm.mapInArrow(tidy(run), T.StructType([*kept, T.StructField("feature", T.StringType())]))


def read_back(media: DataFrame, to: int = 2 * RATE) -> DataFrame:
    """Store ``(doc_id, n_bytes, media)``, tell what the stored bytes hold, store the PCM they give at ``to`` Hz, and describe that.

    Rows without media have nulls for all that is told of it.
    """
    return _read_back(media, to)[0]


def _read_back(media: DataFrame, to: int) -> tuple[DataFrame, list[DataFrame]]:
    held = written(media, "media")
    pcm = written(described_with_pcm(held, to), "pcm")
    return featured(pcm).select("doc_id", "n_bytes", *_TOLD, "feature"), [held, pcm]


def in_parts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", parts: int = PARTS, to: int = 2 * RATE) -> DataFrame:
    """``read_back`` of all texts, stored part by part (by a hash of the text); a part's files go when they have been read back and described."""
    told = []
    for i in range(parts):
        found, files = _read_back(store(docs.where(F.pmod(F.xxhash64(text_col), F.lit(parts)) == i), id_col, text_col), to)
        told.append(materialize(found, "features"))
        discard(*files)
    return reduce(DataFrame.unionByName, told)


def described_with_pcm(media: DataFrame, to: int) -> DataFrame:
    """Stored media once read: digests and resampled PCM side by side."""
    return described(resampled(media, to))


def op9_telephony(spark: SparkSession, sf_dir: str) -> DataFrame:
    return in_parts(read_table(spark, sf_dir, "documents"))
