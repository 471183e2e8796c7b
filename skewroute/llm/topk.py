"""Exact top-k inner-product search by columnar branch and bound.

Candidates lie dimension by dimension in blocks of rows. A query adds up its score one block of dimensions at a time;
after each block the mass that the remaining dimensions can still add (Cauchy-Schwarz on the remaining norms) bounds
every candidate, and those that cannot reach the query's k-th best so far are compacted away. The dimensions of most
query mass go first. Queries are taken in blocks of a fixed number of bytes; one block at a time is broadcast, each
candidate partition answers it with k rows a query at most, and the partial answers are merged per query.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from skewroute.llm.common import materialize, read_table, scratch_path

K = 5
SCALE = 256
DIM_BLOCK = 16
ROW_BLOCK = 4096
#: Bytes of query vectors that one round broadcasts.
QUERY_BYTES = 16 << 20


def quantized(df: DataFrame, id_col: str, vec_col: str, scale: int) -> DataFrame:
    """``(id long, v array<long>)`` of the rows that take part: no null vector, no null or non-finite component."""
    x = F.col(vec_col)
    whole = x.isNotNull() & ~F.exists(x, lambda c: c.isNull() | F.isnan(c.cast("double")) | (F.abs(c.cast("double")) == float("inf")))
    return df.where(F.col(id_col).isNotNull() & whole).select(F.col(id_col).cast("long").alias("id"), F.transform(x, lambda c: F.floor(F.lit(scale) * c.cast("double"))).alias("v"))


def _matrix(vectors: pa.Array, dims: int) -> np.ndarray:
    """Rows of an Arrow list column as one int64 matrix; shorter vectors count as zero beyond their end, longer ones end at ``dims``."""
    vectors = vectors.combine_chunks() if isinstance(vectors, pa.ChunkedArray) else vectors
    ends, flat = vectors.offsets.to_numpy(), vectors.values.to_numpy()
    lengths = np.diff(ends)
    if (lengths == dims).all():
        return flat[ends[0] : ends[-1]].reshape(len(vectors), dims)
    out = np.zeros((len(vectors), dims), np.int64)
    for row, lo, n in zip(out, ends.tolist(), np.minimum(lengths, dims).tolist(), strict=False):
        row[:n] = flat[lo : lo + n]
    return out


class BlockSearch:
    """Best k of each query over blocks of candidates that come one after another."""

    def __init__(self, ids: np.ndarray, queries: np.ndarray, k: int, dim_block: int):
        self.ids, self.k = ids, k
        self.order = np.argsort(-np.abs(queries).sum(axis=0), kind="stable") if len(queries) else np.arange(queries.shape[1])
        self.q = queries[:, self.order]
        self.cuts = [*range(0, queries.shape[1], dim_block), queries.shape[1]]
        self.q_rest = self._rest(self.q)
        self.best = [(np.zeros(0, np.int64), np.zeros(0, np.int64)) for _ in ids]
        self.scored = 0  # components multiplied, to measure what the bounds save

    def _rest(self, x: np.ndarray) -> np.ndarray:
        """Norm of what is left after each block of dimensions."""
        squares = x.astype(np.float64) ** 2
        return np.stack([np.sqrt(squares[:, c:].sum(axis=1)) for c in self.cuts])

    def add(self, ids: np.ndarray, rows: np.ndarray) -> None:
        rows = rows[:, self.order]
        widest = float(np.abs(rows).max(initial=0)) * float(np.abs(self.q).max(initial=0)) * rows.shape[1]
        kind = np.float64 if widest < 2**53 else np.int64  # exact either way; float64 is the fast product
        columns, queries, rest = np.ascontiguousarray(rows.T).astype(kind), self.q.astype(kind), self._rest(rows)
        first = queries[:, : self.cuts[1]] @ columns[: self.cuts[1]] if len(self.cuts) > 1 else np.zeros((len(queries), len(ids)))
        for n, own in enumerate(self.ids):
            top_score, top_id = self.best[n]
            alive, sums = np.flatnonzero(ids != own), first[n]
            sums = sums[alive]
            self.scored += len(alive) * (self.cuts[1] if len(self.cuts) > 1 else 0)
            for b in range(1, len(self.cuts) - 1):
                bound = sums + self.q_rest[b, n] * rest[b][alive] * (1 + 1e-9) + 1e-3
                floor = top_score[-1] if len(top_score) == self.k else None
                if len(alive) > 8 * self.k:
                    # Candidates' own lower bounds raise the bar before any of them is complete.
                    least = sums - self.q_rest[b, n] * rest[b][alive] * (1 + 1e-9) - 1e-3
                    reach = np.partition(least, -self.k)[-self.k]
                    floor = reach if floor is None else max(floor, reach)
                if floor is not None:
                    stay = bound >= floor
                    alive, sums = alive[stay], sums[stay]
                low, high = self.cuts[b], self.cuts[b + 1]
                sums = sums + queries[n, low:high] @ columns[low:high, alive]
                self.scored += len(alive) * (high - low)
            score, found = np.r_[top_score, np.rint(sums).astype(np.int64) if kind is np.float64 else sums.astype(np.int64)], np.r_[top_id, ids[alive]]
            pick = np.lexsort((found, -score))[: self.k]
            self.best[n] = (score[pick], found[pick])


def exact_top_k(rows: DataFrame, queries: DataFrame, k: int = K, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = SCALE, dim_block: int = DIM_BLOCK, row_block: int = ROW_BLOCK, query_bytes: int = QUERY_BYTES) -> DataFrame:
    """``(query_id, rank, vec_id, score)``: the k highest integer inner products of each query, ties to smaller ids.

    Rows with a null id take no part; a row with the query's own id is no candidate of it. Repeated ids: each row is
    a candidate, and of the query rows with one id the least vector asks. Vectors of differing length count as zero
    beyond their end. An empty table gives an empty table. Other columns are not read.

    One block of queries at a time is broadcast; its answers are written before the next one goes out, so that neither the
    plan nor what is held grows with the number of queries.
    """
    spark = rows.sparkSession
    base = quantized(rows, id_col, vec_col, scale)
    asked = materialize(quantized(queries, id_col, vec_col, scale).groupBy("id").agg(F.min("v").alias("v")), "queries")
    count, dims = asked.agg(F.count("*"), F.max(F.size("v"))).first()
    if not count:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    rounds = -(-count * max(dims, 1) * 8 // query_bytes)
    found = [_answers(spark, base, asked.where(F.pmod(F.xxhash64("id"), F.lit(rounds)) == r), dims, k, dim_block, row_block) for r in range(rounds)]
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    out = spark.read.schema(_FOUND).parquet(*found)
    return out.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


_FOUND = "query_id long, vec_id long, score long"


def _answers(spark: SparkSession, base: DataFrame, block: DataFrame, dims: int, k: int, dim_block: int, row_block: int) -> str:
    """Where the best k of each partition for one block of queries have been written."""
    held = block.toArrow()
    shared = spark.sparkContext.broadcast((held.column("id").to_numpy(), _matrix(held.column("v"), dims)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = BlockSearch(*shared.value, k, dim_block)
        for b in batches:
            for i in range(0, b.num_rows, row_block):
                part = b.slice(i, row_block)
                search.add(part.column("id").to_numpy(), _matrix(part.column("v"), dims))
        for q, (score, i) in zip(search.ids.tolist(), search.best, strict=True):
            if len(i):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(i), q)), pa.array(i), pa.array(score)], ["query_id", "vec_id", "score"])

    path = scratch_path(spark, "answers")
    base.mapInArrow(run, _FOUND).write.parquet(path)
    shared.destroy()
    return path


def op10_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return exact_top_k(rows, rows.where("vec_id % 50 = 0"))


ORACLE = """
WITH q AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
flat AS (SELECT vec_id, unnest(v) AS x, generate_subscripts(v, 1) AS d FROM q),
s AS (
  SELECT a.vec_id AS query_id, b.vec_id AS vec_id, sum(a.x * b.x)::BIGINT AS score
  FROM flat a JOIN flat b ON a.d = b.d AND a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0 GROUP BY ALL)
SELECT query_id, rank, vec_id, score FROM (
  SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM s)
WHERE rank <= 5
"""
