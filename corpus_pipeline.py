"""A corpus pipeline of five operators: quality classifier, near-duplicates, repeated passages, mixing, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from skewroute.llm import mixing, packing, quality, simhash, substring
from skewroute.llm.common import materialize, read_table

#: Each stage takes (spark, docs, sf_dir); all but the last return the columns of documents.
STAGES = [
    ("quality_classifier", quality.quality_stage),
    ("simhash_near_dedup", simhash.near_copy_stage),
    ("substring_dedup", substring.substring_stage),
    ("source_mixing", mixing.mixing_stage),
    ("best_fit_packing", packing.packing_stage),
]

#: The first four stages and the tokenizer are beyond SQL; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return docs
