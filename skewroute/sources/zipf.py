"""Zipf key streams on the rows of any table, and a Python data source that makes them from nothing.

Weights are integers so that a row draws the same rank in any engine: 32 bits of an md5 of the row's draw text, scaled
to the total weight in integer arithmetic, looked up in the running sums of the weights.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import pandas_udf

SCALE = 10**8


def zipf_weights(keys: int, z: float, scale: int = SCALE) -> np.ndarray:
    """Integer weights of ranks 1 to ``keys``; the scale goes down by tens until the total is below 2^31."""
    k = np.arange(1, keys + 1, dtype=np.float64)
    whole = float(z).is_integer()
    while True:
        w = scale // np.arange(1, keys + 1, dtype=np.int64) ** int(z) if whole and keys ** int(z) < 2**62 else np.rint(scale * k ** -float(z)).astype(np.int64)
        if w.sum() < 2**31:
            return w
        scale //= 10


def zipf_scale(keys: int, z: float) -> int:
    """The scale that the weights end up with."""
    scale = SCALE
    while (scale // np.arange(1, keys + 1, dtype=np.int64) ** int(z) if float(z).is_integer() else np.rint(scale * np.arange(1, keys + 1, dtype=np.float64) ** -float(z)).astype(np.int64)).sum() >= 2**31:
        scale //= 10
    return scale


def zipf_shares(keys: int, z: float) -> np.ndarray:
    """Exact shares, hottest first."""
    p = np.arange(1, keys + 1, dtype=np.float64) ** -float(z)
    return p / p.sum()


def uniform_bits(text: Column, seed: int = 7) -> Column:
    """32 bits of a row, as a long."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), text)), 1, 8), 16, 10).cast("long")


def zipf_rank(text: Column, keys: int, z: float, seed: int = 7) -> Column:
    """The rank (from 1) that a row draws. The cuts are ``keys`` numbers, sent with the function."""
    cuts = np.cumsum(zipf_weights(keys, z))

    @pandas_udf("int")
    def look_up(u: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(cuts, u.to_numpy(), side="right") + 1)

    return look_up(F.shiftright(uniform_bits(text, seed) * int(cuts[-1]), 32))


def zipf_events(spark: SparkSession, folder: str, keys: int, z: float, seed: int = 7) -> DataFrame:
    """``(seq, ts, key)`` on the rows of events; keys are ranks as text."""
    events = spark.read.parquet(f"{folder}/events.parquet")
    return events.select(F.col("event_id").alias("seq"), "ts", zipf_rank(F.col("event_id").cast("string"), keys, z, seed).cast("string").alias("key"))


def lineitem_draw() -> Column:
    return F.concat_ws(",", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def zipf_lineitem(spark: SparkSession, folder: str, keys: int, z: float, seed: int = 7) -> DataFrame:
    """``(seq, key)`` on the rows of lineitem; ``seq`` is a hash of the row, an order but not a dense one."""
    rows = spark.read.parquet(f"{folder}/lineitem.parquet")
    return rows.select(F.xxhash64(*rows.columns).alias("seq"), zipf_rank(lineitem_draw(), keys, z, seed).cast("string").alias("key"))


def zipf_range(spark: SparkSession, m: int, keys: int, z: float, seed: int = 7, partitions: int | None = None) -> DataFrame:
    """``m`` messages from a range, for loads of any size."""
    ids = spark.range(m, numPartitions=partitions) if partitions else spark.range(m)
    return ids.select(F.col("id").alias("seq"), zipf_rank(F.col("id").cast("string"), keys, z, seed).cast("string").alias("key"))


def drift_events(spark: SparkSession, folder: str, keys: int, z: float, shift: int = 97, seed: int = 7) -> DataFrame:
    """A stream whose hot keys move: the rank plus ``shift`` for each day since the first of 2024, modulo ``keys``."""
    drawn = zipf_events(spark, folder, keys, z, seed)
    day = F.datediff(F.to_date("ts"), F.to_date(F.lit("2024-01-01")))
    return drawn.select("seq", "ts", ((F.col("key").cast("long") + shift * day) % keys).cast("string").alias("key"))


def visits(spark: SparkSession, folder: str, z: float = 1.0, seed: int = 7) -> DataFrame:
    """Page visits ``(seq, key)``: each row of lineitem visits the page of the rank it draws; the key is the URL."""
    pages = spark.read.parquet(f"{folder}/pages.parquet").select((F.col("page_id") + 1).cast("string").alias("key"), "url")
    drawn = zipf_lineitem(spark, folder, pages.count(), z, seed)
    return drawn.join(pages, "key").select("seq", F.col("url").alias("key"))


class _Rows(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class ZipfSource(DataSource):
    """``spark.read.format("zipf").option("rows", m).option("keys", k).option("z", z).load()``."""

    @classmethod
    def name(cls) -> str:
        return "zipf"

    def schema(self) -> str:
        return "seq long, key string"

    def reader(self, schema) -> DataSourceReader:
        return ZipfReader(self.options)


class ZipfReader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.keys, self.z = int(options.get("rows", 1000)), int(options.get("keys", 100)), float(options.get("z", 1.0))
        self.parts, self.seed = int(options.get("partitions", 4)), int(options.get("seed", 7))

    def partitions(self) -> list[InputPartition]:
        cuts = [self.rows * i // self.parts for i in range(self.parts + 1)]
        return [_Rows(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition: _Rows) -> Iterator[tuple]:
        sums = np.cumsum(zipf_weights(self.keys, self.z))
        draw = np.random.default_rng([self.seed, partition.first])
        for at in range(partition.first, partition.last, 1 << 16):
            n = min(1 << 16, partition.last - at)
            ranks = np.searchsorted(sums, draw.integers(0, sums[-1], n), side="right") + 1
            yield from zip(range(at, at + n), map(str, ranks.tolist()), strict=True)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ZipfSource)
