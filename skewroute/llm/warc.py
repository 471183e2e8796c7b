"""Dictionary-compressed web archives: WARC 1.1 records in individually compressed Zstandard frames.

An archive starts with a skippable frame that holds the dictionary, built from records of that archive; every record
is a frame of its own, so one record can be read alone. Archives are rows of chunks ``(archive, seq, chunk)``: the
chunks of an archive in order are the bytes of a ``.warc.zst`` file. They are rows so that any store Spark writes to
can hold them; ``export_files`` makes files on a shared mount and ``read_files`` reads such files.
"""

from __future__ import annotations

import base64
import hashlib
import io
import struct
import uuid
from collections.abc import Iterator
from pathlib import Path
from urllib.parse import quote

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skewroute.llm.common import materialize, read_table

#: Magic number of the skippable frame that holds a dictionary.
DICTIONARY_MAGIC = 0x184D2A5D
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "1970-01-01T00:00:00Z"
ARCHIVE_BYTES = 32 << 20
CHUNK_BYTES = 1 << 20
SAMPLE_BYTES = 1 << 20
DICTIONARY_BYTES = 32 << 10
_URN = "urn:page:"


def record(page_id: int, url: str | None, payload: bytes, digest: str, refers_to: int | None, date: str = DATE) -> bytes:
    """One WARC record around an HTTP response; a revisit leaves the payload out and names the record that has it."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if refers_to is not None else http + payload
    head = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <{f'{_URN}{page_id}' if page_id is not None else uuid.uuid4().urn}>",
        f"WARC-Date: {date}",
        f"WARC-Target-URI: {quote(url, safe=':/?#[]@!$&()*+,;=%~') if url is not None else 'about:blank'}",
        f"WARC-Payload-Digest: sha1:{digest}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if refers_to is not None:
        head += [f"WARC-Profile: {REVISIT_PROFILE}", f"WARC-Refers-To: <{_URN}{refers_to}>"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def build_dictionary(samples: list[bytes]) -> bytes:
    """A trained dictionary, or the samples' own bytes where there are too few to train on."""
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples, level=3).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[-DICTIONARY_BYTES:]


def _dictionary(data: bytes) -> zstandard.ZstdCompressionDict:
    return zstandard.ZstdCompressionDict(data)


class ArchiveWriter:
    """Takes records one by one and gives chunks; holds one sample and one chunk at most."""

    def __init__(self, level: int = 3, archive_bytes: int = ARCHIVE_BYTES, sample_bytes: int = SAMPLE_BYTES, chunk_bytes: int = CHUNK_BYTES):
        self.level, self.archive_bytes, self.sample_bytes, self.chunk_bytes = level, archive_bytes, sample_bytes, chunk_bytes
        self._begin()

    def _begin(self) -> None:
        self.name, self.seq, self.size = uuid.uuid4().hex, 0, 0
        self.sample: list[bytes] = []
        self.sampled, self.pack, self.chunk = 0, None, bytearray()

    def _start(self) -> None:
        data = build_dictionary(self.sample)
        self.pack = zstandard.ZstdCompressor(level=self.level, dict_data=_dictionary(data), write_content_size=True)
        body = zstandard.ZstdCompressor(level=19).compress(data)
        self.chunk += struct.pack("<II", DICTIONARY_MAGIC, len(body)) + body
        for r in self.sample:
            self.chunk += self.pack.compress(r)
        self.sample = []

    def _cut(self) -> Iterator[tuple[str, int, bytes]]:
        if self.chunk:
            yield self.name, self.seq, bytes(self.chunk)
            self.seq, self.size, self.chunk = self.seq + 1, self.size + len(self.chunk), bytearray()

    def add(self, r: bytes) -> Iterator[tuple[str, int, bytes]]:
        if self.pack is None:
            self.sample.append(r)
            self.sampled += len(r)
            if self.sampled < self.sample_bytes:
                return
            self._start()
        else:
            self.chunk += self.pack.compress(r)
        if len(self.chunk) >= self.chunk_bytes:
            yield from self._cut()
            if self.size >= self.archive_bytes:
                self._begin()

    def close(self) -> Iterator[tuple[str, int, bytes]]:
        if self.pack is None and self.sample:
            self._start()
        yield from self._cut()


class ArchiveReader:
    """Takes the chunks of an archive in order and gives its records as ``(headers, block)``."""

    def __init__(self):
        self.unpack: zstandard.ZstdDecompressor | None = None

    def records(self, chunk: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
        if self.unpack is None:
            magic, n = struct.unpack_from("<II", chunk)
            if magic != DICTIONARY_MAGIC:
                raise ValueError("an archive starts with its dictionary")
            data = zstandard.ZstdDecompressor().decompress(chunk[8 : 8 + n])
            self.unpack, chunk = zstandard.ZstdDecompressor(dict_data=_dictionary(data)), chunk[8 + n :]
        stream = io.BufferedReader(self.unpack.stream_reader(chunk, read_across_frames=True), 1 << 16)
        while line := stream.readline():
            if not line.startswith(b"WARC/"):
                raise ValueError("a record starts with its version")
            headers = {}
            while (line := stream.readline()) not in (b"\r\n", b""):
                name, _, value = line.decode().partition(":")
                headers[name.lower()] = value.strip()
            block = stream.read(int(headers["content-length"]))
            if stream.read(4) != b"\r\n\r\n":
                raise ValueError("a record ends with two empty lines")
            yield headers, block


def classify(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """Add ``_payload`` (UTF-8 of html, null: empty), ``_sha1`` (hex) and ``_first`` (page a revisit refers to, else null).

    The least page of each payload comes from one map-side combined aggregate of ids by digest. The join back splits
    a digest that many pages share, as a skewed join.
    """
    keyed = pages.select("page_id", "url", F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("_payload")).withColumn("_sha1", F.sha1("_payload"))
    narrow = pages.select("page_id", F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("_p")).where(F.octet_length("_p") >= least_bytes)
    first = narrow.groupBy(F.sha1("_p").alias("_sha1")).agg(F.min("page_id").alias("_least"), F.count("*").alias("_n")).where("_n > 1").drop("_n")
    joined = keyed.join(first, "_sha1", "left")
    return joined.withColumn("_first", F.when(F.col("page_id") != F.col("_least"), F.col("_least"))).drop("_least")


def write_archives(pages: DataFrame, least_bytes: int = 0, level: int = 3, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """``(archive, seq, chunk)`` of ``pages(page_id, url, html)``, written to the shared folder.

    Of pages with equal payloads of at least ``least_bytes`` the smallest id is the response and the others revisit
    it; rows that repeat the smallest id are responses too. Null ids take part as revisits only of no one: they are
    responses. An empty table gives no archive.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(chunks: list[tuple[str, int, bytes]]) -> pa.RecordBatch:
            names, seqs, data = zip(*chunks, strict=True)
            return pa.RecordBatch.from_arrays([pa.array(names), pa.array(seqs, pa.int64()), pa.array(data, pa.binary())], ["archive", "seq", "chunk"])

        writer = ArchiveWriter(level, archive_bytes)
        for b in batches:
            for page, url, payload, sha1, first in zip(*(b.column(c) for c in ("page_id", "url", "_payload", "_sha1", "_first")), strict=True):
                digest = base64.b32encode(bytes.fromhex(sha1.as_py())).decode()
                if chunks := list(writer.add(record(page.as_py(), url.as_py(), payload.as_py(), digest, first.as_py()))):
                    yield out(chunks)
        if chunks := list(writer.close()):
            yield out(chunks)

    return materialize(classify(pages, least_bytes).mapInArrow(run, "archive string, seq long, chunk binary"), "archives")


def _describe(headers: dict[str, str], block: bytes) -> tuple:
    """The page id, payload length, digest, type and target of one record, and its payload (null in a revisit).

    Length and digest of a response are those of the payload that was read; a record whose headers say otherwise is damaged. A
    revisit holds no payload: what its headers say is ``check_revisits``' to compare with the response.
    """
    head, _, body = block.partition(b"\r\n\r\n")
    length = next(int(line.partition(b":")[2]) for line in head.split(b"\r\n") if line.lower().startswith(b"content-length:"))
    page, target = (headers.get(h, "").strip("<>") for h in ("warc-record-id", "warc-refers-to"))
    kind, digest = headers["warc-type"], headers["warc-payload-digest"].partition(":")[2]
    if kind == "response":
        found = base64.b32encode(hashlib.sha1(body).digest()).decode()
        if found != digest or len(body) != length:
            raise ValueError(f"the payload of {page} is not what its record says")
        length, digest = len(body), found
    own = int(page.removeprefix(_URN)) if page.startswith(_URN) else None
    return own, length, digest, kind, int(target.removeprefix(_URN)) if target else None, body if kind == "response" else None


_ROW = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]
_KINDS = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary())
_SCHEMA = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"


def _rows(records: Iterator[tuple[dict[str, str], bytes]]) -> Iterator[pa.RecordBatch]:
    held, size = [], 0
    for r in records:
        held.append(_describe(*r))
        size += len(r[1])
        if size > 8 << 20:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held, strict=True), _KINDS, strict=True)], _ROW)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held, strict=True), _KINDS, strict=True)], _ROW)


def read_archives(archives: DataFrame) -> DataFrame:
    """Every record of the archives: ids, digests, types and, for responses, payloads. Archives are of bounded size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def records() -> Iterator[tuple[dict[str, str], bytes]]:
            name, reader = None, None
            for b in batches:
                for archive, chunk in zip(b.column("archive"), b.column("chunk"), strict=True):
                    if archive.as_py() != name:
                        name, reader = archive.as_py(), ArchiveReader()
                    yield from reader.records(chunk.as_py())

        yield from _rows(records())

    return archives.repartition("archive").sortWithinPartitions("archive", "seq").mapInArrow(run, _SCHEMA)


def export_files(archives: DataFrame, folder: str) -> DataFrame:
    """Write each archive as ``<archive>.warc.zst`` in a folder that all executors mount; ``(archive, bytes)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sizes: dict[str, int] = {}
        for b in batches:
            for archive, seq, chunk in zip(*(b.column(c).to_pylist() for c in ("archive", "seq", "chunk")), strict=True):
                with Path(folder, f"{archive}.warc.zst").open("ab" if seq else "wb") as f:
                    f.write(chunk)
                sizes[archive] = sizes.get(archive, 0) + len(chunk)
        yield pa.RecordBatch.from_arrays([pa.array(list(sizes), pa.string()), pa.array(list(sizes.values()), pa.int64())], ["archive", "bytes"])

    return archives.repartition("archive").sortWithinPartitions("archive", "seq").mapInArrow(run, "archive string, bytes long")


def read_files(spark: SparkSession, path: str) -> DataFrame:
    """Records of ``.warc.zst`` files under a path of any file system."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for content in b.column("content"):
                yield from _rows(ArchiveReader().records(content.as_py()))

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.zst").load(path)
    return files.select("content").mapInArrow(run, _SCHEMA)


def check_revisits(records: DataFrame) -> None:
    """Fail where a revisit's length and digest are not those of a payload that was read from the record it refers to.

    What is compared is a row for each page that has revisits, found by an aggregate, whatever their number.
    """
    what = ["payload_digest", "payload_bytes"]
    asked = records.where("record_type = 'revisit'").select(F.col("refers_to").alias("page_id"), *what).distinct()
    lost = asked.join(records.where("record_type = 'response'").select("page_id", *what), ["page_id", *what], "left_anti").count()
    if lost:
        raise ValueError(f"{lost} payloads that revisits refer to are not in the archives")


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    records = materialize(read_archives(write_archives(read_table(spark, sf_dir, "pages"))).drop("payload"), "records")
    check_revisits(records)
    return records


ORACLE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h, sha1(coalesce(html, '')) AS d FROM pages),
f AS (SELECT d, min(page_id) AS first FROM p GROUP BY d),
b AS (SELECT d, array_to_string(list_transform(range(8), lambda g: array_to_string(list_transform([15, 10, 5, 0],
  lambda s: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((('0x' || substr(d, 1 + 5 * g::INT, 5))::BIGINT >> s) & 31)::INT, 1)), '')), '') AS digest FROM f)
SELECT page_id, strlen(h)::BIGINT AS payload_bytes, digest AS payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> first THEN first END AS refers_to
FROM p JOIN f USING (d) JOIN b USING (d)
"""
