"""Tables as keyed message streams ``(seq, ts, key, value)``."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: What may be a key. Floating numbers and maps have no dependable equality or hash.
_REFUSED = (T.FloatType, T.DoubleType, T.MapType)


def read_table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read_any(spark: SparkSession, form: str, path: str, schema: T.StructType | str | None = None, **options) -> DataFrame:
    """A batch table of any of Spark's formats (parquet, orc, json, csv, text...)."""
    reader = spark.read.format(form).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def as_messages(df: DataFrame, key: str | Column, order: str | Column, ts: str | Column | None = None, value: str | Column | None = None, drop_null_keys: bool = False) -> DataFrame:
    """Project a table to messages: ``seq`` orders them, ``key`` becomes a string (null is a key of its own)."""
    col = lambda c: F.col(c) if isinstance(c, str) else c
    out = df.select(col(order).cast("long").alias("seq"), (col(ts).cast("timestamp") if ts is not None else F.lit(None).cast("timestamp")).alias("ts"), col(key).alias("key"), (col(value).cast("double") if value is not None else F.lit(1.0)).alias("value"))
    kind = out.schema["key"].dataType
    if isinstance(kind, _REFUSED):
        raise TypeError(f"keys of type {kind.simpleString()} are refused")
    text = F.to_json("key") if isinstance(kind, (T.StructType, T.ArrayType)) else F.hex("key") if isinstance(kind, T.BinaryType) else F.col("key").cast("string")
    out = out.withColumn("key", text)
    return out.where("key IS NOT NULL") if drop_null_keys else out


def composite_key(*columns: str | Column) -> Column:
    """Several columns as one key."""
    return F.concat_ws("|", *(F.col(c).cast("string") if isinstance(c, str) else c for c in columns))


def event_messages(spark: SparkSession, folder: str, key: str = "event_type") -> DataFrame:
    return as_messages(read_table(spark, folder, "events"), key, "event_id", "ts", "value")


def tokens(spark: SparkSession, folder: str, table: str = "documents", key: str = "doc_id") -> DataFrame:
    """``(key id, pos, key)``: one message a word, texts split at single spaces."""
    docs = read_table(spark, folder, table)
    return docs.select(F.col(key), F.posexplode(F.split("text", " ", -1)).alias("pos", "key"))


def token_messages(spark: SparkSession, folder: str) -> DataFrame:
    """Words of documents as messages; ``seq`` is document and place in one long, so it orders but is not dense."""
    return tokens(spark, folder).select((F.col("doc_id") * (1 << 24) + F.col("pos")).alias("seq"), "key")


def hosts(spark: SparkSession, folder: str) -> DataFrame:
    pages = read_table(spark, folder, "pages")
    return pages.select(F.col("page_id").alias("seq"), F.regexp_extract("url", "^[a-z]+://([^/?#]*)", 1).alias("key"))


def links(spark: SparkSession, folder: str) -> DataFrame:
    """Links in pages as visits, in page order."""
    pages = read_table(spark, folder, "pages")
    found = pages.select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("pos", "key"))
    return found.select((F.col("page_id") * (1 << 20) + F.col("pos")).alias("seq"), "key")
