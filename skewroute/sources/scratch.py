"""Tables written to the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def _root(spark: SparkSession) -> str:
    """The application's own folder under ``spark.checkpoint.dir``. Where that is unset, a local session makes a folder for itself; a cluster has to name one."""
    shared = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not shared:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="skewroute-"))
        shared = spark.sparkContext.getCheckpointDir()
    return f"{shared.rstrip('/')}/skewroute/{spark.sparkContext.applicationId}"


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path that all executors share."""
    return f"{_root(spark)}/{name}-{uuid.uuid4().hex}"


def drop_scratch(spark: SparkSession) -> bool:
    """Delete what this application has written there. Results that still read it must be stored first."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(_root(spark))
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def write_routed(routed: DataFrame, path: str) -> None:
    """One folder a worker."""
    routed.write.partitionBy("worker").parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str = "key") -> None:
    """A table whose joins and aggregates on the key need no exchange."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write and read back: routed rows that several measures use are routed once."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def delete_path(spark: SparkSession, path: str) -> None:
    """Delete a folder of any file system that Spark writes to."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def discard(*tables: DataFrame) -> None:
    """Delete materialised tables that nothing will read again."""
    for t in tables:
        if path := getattr(t, "_scratch_path", None):
            delete_path(t.sparkSession, path)
