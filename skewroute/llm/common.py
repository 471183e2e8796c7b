"""Helpers shared by the training-data operators: table access, scratch tables, hashing of words."""

from __future__ import annotations

import ctypes
import functools
import gc
import itertools
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from skewroute.sources import scratch
from skewroute.sources.scratch import delete_path, discard, scratch_path

__all__ = ["BITMAP_BITS", "HOT_KEYS", "WORD_PATTERN", "bit_set", "bitmap_of", "delete_path", "discard", "free_shuffles", "in_bitmap", "input_bytes", "input_partitions", "join_counted", "materialize", "portions", "read_table", "release_memory", "scratch_path", "tidy", "trim_driver", "words_of"]

#: A word is a maximal run of characters other than space and U+0009..U+000D, so ``bytes.split()`` finds exactly these.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
#: Size of the bitmaps of hashed keys that scans are sent; more keys cost more false hits, nothing else.
BITMAP_BITS = 1 << 26
#: A key with more than one in so many of all rows is joined by broadcast: there are at most so many such keys.
HOT_KEYS = 4096
#: Rows whose texts a Python worker unpacks at a time.
PORTION = 512
#: Tables that are written and read back between two times that the driver lets go of their plans.
FREE_EVERY = 8


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The Parquet table ``name`` of a data folder, through Spark's own reader (any file system)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words_of(text: str | None) -> list[bytes]:
    """The words of a text as UTF-8 bytes (null: none)."""
    return (text or "").encode("utf-8", "surrogatepass").split()


def input_partitions(df: DataFrame) -> int:
    """How many partitions a scan is dealt over; follows the size of the input."""
    return max(1, df.rdd.getNumPartitions())


def input_bytes(df: DataFrame) -> int | None:
    """What the tables behind a plan take where they are stored, as Spark's planner knows it; None where it does not (rows made by hand)."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    sizes = [int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size())]
    return None if max(sizes, default=0) >= 1 << 60 else sum(sizes)


def trim_driver(spark: SparkSession) -> str | None:
    """Have the driver's JVM give the system back what its native code has freed (what threads, compilers and codecs took by malloc), which would stay
    beside the heap for good. Told by the JVM's own diagnostic command; one that has no such command keeps what it has (None)."""
    jvm = spark.sparkContext._jvm
    args = spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 4)
    try:
        # By reflection: the server's own class is not exported.
        invoke = next(m for m in jvm.java.lang.Class.forName("javax.management.MBeanServer").getMethods() if m.getName() == "invoke")
        args[0], args[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        return str(invoke.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), args))
    except Py4JError:
        return None


def free_shuffles(spark: SparkSession) -> None:
    """Let go of the shuffle files of plans that nothing refers to any more: Spark drops them when the driver's collector finds the plans gone, which on
    a driver with little to collect may be long after. What the driver has freed goes back to the system."""
    gc.collect()
    spark.sparkContext._jvm.java.lang.System.gc()
    trim_driver(spark)


_written = itertools.count(1)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write and read back, as ``scratch.materialize``; after every ``FREE_EVERY`` tables the driver lets go of what planned and ran them."""
    out = scratch.materialize(df, name)
    if next(_written) % FREE_EVERY == 0:
        free_shuffles(df.sparkSession)
    return out


@functools.cache
def _trim() -> Callable[[int], int] | None:
    return getattr(ctypes.CDLL(None), "malloc_trim", None)


def release_memory() -> None:
    """Give back what has been freed: Python workers outlive their tasks, and would keep it beside the next stage's."""
    pa.default_memory_pool().release_unused()
    if trim := _trim():
        trim(0)


def tidy(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """A batch function that releases memory when its task is done."""

    @functools.wraps(run)
    def wrapped(batches: Iterator) -> Iterator:
        yield from run(batches)
        release_memory()

    return wrapped


def portions(batches: Iterator[pa.RecordBatch], rows: int = PORTION) -> Iterator[pa.RecordBatch]:
    """The batches in slices of at most ``rows`` rows: a batch of 10,000 long texts need not be there as Python strings at once."""
    for b in batches:
        yield from (b.slice(at, rows) for at in range(0, b.num_rows, rows))


def bit_set(bitmap: np.ndarray, a: np.ndarray) -> np.ndarray:
    at = a & np.uint64(64 * len(bitmap) - 1)
    return (bitmap[at >> np.uint64(6)] >> (at & np.uint64(63)) & np.uint64(1)).astype(bool)


def in_bitmap(rows: DataFrame, bitmap: Broadcast, key: str = "a", there: bool = True) -> DataFrame:
    """Rows whose key may be in the bitmap; a join with the keys themselves must follow. Or those whose key is not (``there=False``)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array(bit_set(bitmap.value, b.column(key).to_numpy().view(np.uint64)) == there))

    return rows.mapInArrow(tidy(run), rows.schema)


def bitmap_of(keys: DataFrame, limit: int = BITMAP_BITS, key: str = "a") -> Broadcast:
    """A bit per key, sent out: 16 bits or more a key up to ``limit`` bits in all (a power of two). At most ``limit / 64`` rows reach the driver, as
    Arrow columns. Destroy it once what reads it has been written."""
    spark, n = keys.sparkSession, keys.count()
    bits = min(limit, 1 << max(6, (16 * n).bit_length()))
    at = F.col(key).bitwiseAND(F.lit(bits - 1))
    words = keys.select(F.shiftright(at, 6).alias("w"), F.expr(f"shiftleft(1L, int({key} & 63))").alias("v")).groupBy("w").agg(F.bit_or("v").alias("v")).toArrow()
    out = np.zeros(bits // 64, np.uint64)
    out[words.column("w").to_numpy()] = words.column("v").to_numpy().view(np.uint64)
    return spark.sparkContext.broadcast(out)


def join_counted(left: DataFrame, right: DataFrame, keys: list[str], total: int, small: Column | None = None) -> DataFrame:
    """Inner join with ``right``, one row a key, whose ``c`` tells how many of ``total`` rows of the left have the key.

    Keys with more than one in ``HOT_KEYS`` of the rows, so at most ``HOT_KEYS`` of them, are broadcast, those alone whose row is ``small``
    where rows are not narrow anyway; a task of the other join gets no more than that part of one key's rows.
    """
    hot = F.col("c") * HOT_KEYS > total
    hot = hot if small is None else hot & small
    few, many = F.broadcast(right.where(hot)), right.where(~hot)
    return left.join(few, keys).unionByName(left.join(few.select(*keys), keys, "left_anti").join(many, keys))
