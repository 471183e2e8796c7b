"""What operators hold at once: texts in workers, plans and freed memory on the driver."""

import random

import pyarrow as pa

from skewroute.llm import common, substring
from tests.llm.conftest import SCHEMA, prose


def test_texts_are_unpacked_in_portions():
    b = pa.RecordBatch.from_pydict({"k": list(range(1200)), "t": [str(i) for i in range(1200)]})
    parts = list(common.portions([b, b.slice(0, 0), b.slice(3, 2)], 500))
    assert [p.num_rows for p in parts] == [500, 500, 200, 2]
    assert sum((p.column("t").to_pylist() for p in parts), []) == [*map(str, range(1200)), "3", "4"]


def test_texts_pass_one_worker_where_they_are_scanned(spark):
    rng = random.Random(8)
    passage = prose(rng, 60)
    rows = [(i, prose(rng, 30) + (" " + passage if i % 400 == 0 else ""), "en", "a", 1) for i in range(1300)] + [(None, passage, "en", "a", 1), (2000, None, "en", "a", 1)]
    docs = spark.createDataFrame(rows, SCHEMA).repartition(1)
    out = substring.remove_repeats(docs, substring.repeated_windows(docs, batches=2), "doc_id", "text", substring.WINDOW, ["doc_id"], digest=True)
    # Of rows that are settled where they are scanned one worker holds the texts; those dealt out have a filter before and the removal behind the exchange.
    assert out._jdf.queryExecution().optimizedPlan().toString().count("MapInArrow") == 3
    told = {r["row"]["doc_id"]: (r["n_words"], r["n_removed"]) for r in out.collect()}
    assert len(told) == len(rows) and {d for d, (_, gone) in told.items() if gone} == {400, 800, 1200}
    assert all(told[d] == (90, 60) for d in (400, 800, 1200)) and told[0] == (90, 0) and told[None] == (60, 0) and told[2000] == (0, 0)


def test_driver_lets_go_between_tables(spark, monkeypatch):
    freed = []
    monkeypatch.setattr(common, "free_shuffles", freed.append)
    for _ in range(2 * common.FREE_EVERY):
        common.materialize(spark.range(1), "few")
    assert len(freed) == 2
    assert (told := common.trim_driver(spark)) is None or "rim" in told
