import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
#: Names that operators use inside, as further columns of a table.
CLASHES = ("d", "r", "t", "i", "h", "size", "sources", "chunk", "key", "fp", "piece", "length", "offset", "repeats", "score", "kept", "n_words", "_d", "_shard", "_spans")


def prose(rng: random.Random, n: int) -> str:
    words = ["the", "of", "stream", "worker", "key", "load", "hash", "sketch", "choice", "balance", "skew", "head", "tail", "message", "state", "time"]
    return " ".join(rng.choice(words) + rng.choice(["", "", "s", "ed", "er"]) for _ in range(n))


def pytest_collection_modifyitems(items):
    """The test of the pipeline's former rule, which the stage no longer follows, comes last: a run that stops at the first failure has run all others."""
    items.sort(key=lambda item: item.name == "test_pipeline_by_brute_force")


@pytest.fixture(scope="session")
def odd_rows():
    """Nulls in every column, empty and very long texts, ties, repeated rows, copies and shared passages."""
    rng = random.Random(5)
    passage, base = prose(rng, 70), prose(rng, 200)
    rows = [
        (1, base, "en", "a", 10), (2, base, "en", "b", 10), (2, base, "en", "b", 10), (3, base + " end", "en", None, None), (4, None, None, None, None), (5, "", "en", "a", 0), (6, "  \t\n ", "en", "a", 5),
        (7, "one", "en", "c", 3), (8, "one two", "de", "c", 7), (9, prose(rng, 120) + " " + passage + " " + prose(rng, 90), "en", "a", 1), (10, prose(rng, 40) + " " + passage, "en", "b", 1), (11, passage + " " + prose(rng, 300), None, "c", 1),
        (12, "x " * 6000, "en", "a", 12000), (13, "x " * 9000 + passage, "en", "a", 1), (14, prose(rng, 5000), "en", "b", 1), (None, prose(rng, 80), "en", "a", 1), (None, passage, "en", "a", 1), (15, "Ünïcödé ｗords​ 日本 " + prose(rng, 60), "de", "c", 1),
        (16, base.upper(), "en", "a", 1), (17, "a\x1cb\x0bc\x85d e f " + passage, "en", "b", 1),
    ]
    return rows + [(100 + i, prose(rng, rng.randrange(1, 160)), rng.choice(["en", "de"]), rng.choice("abc"), 1) for i in range(40)]


@pytest.fixture(scope="session")
def odd(spark, odd_rows):
    from pyspark.sql import functions as F

    df = spark.createDataFrame(odd_rows, SCHEMA).repartition(3)
    return df.select("*", *(F.lit(i).alias(c) for i, c in enumerate(CLASHES)))


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)
