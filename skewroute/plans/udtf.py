"""Routing from SQL: ``SELECT * FROM route_messages(TABLE(m) PARTITION BY source_id ORDER BY (seq), scheme, workers)``."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from skewroute.functions.hashing import md5_choice
from skewroute.operators.kernel import Router, Scheme


@udtf(returnType="seq long, source_id int, key string, worker int, is_head boolean, n_choices int")
class RouteMessages:
    """Takes rows with ``seq``, ``source_id`` and ``key``; one instance a source."""

    def __init__(self):
        self.router = None

    def eval(self, row, scheme: str, workers: int):
        if self.router is None:
            self.router = Router(Scheme(scheme), workers, row["source_id"])
        key = row["key"]
        w, h, d = self.router.step(key, md5_choice(key, 1, workers), md5_choice(key, 2, workers))
        yield row["seq"], row["source_id"], key, w, h, d


def register(spark: SparkSession) -> None:
    spark.udtf.register("route_messages", RouteMessages)
