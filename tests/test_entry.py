"""The entry works with and without the training-data part."""

import os
import shutil
import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[1]
SAY = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); print(len(q), 'pipeline' in q, any(k.startswith('op') for k in q), set(o) <= set(q))"
RUN = """
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[2]").config("spark.sql.shuffle.partitions", "2").config("spark.ui.enabled", "false").getOrCreate()
import __spark_entry__ as e
q = e.queries()
print(*(q[k](spark, "/root/testdata/sf0.001").count() for k in ("key_grouping_load", "two_choice_assign", "exact_head_tokens", "balanced_word_count")), e.entry(spark).count())
"""


def told(folder, code=SAY):
    run = subprocess.run([sys.executable, "-c", code], cwd=folder, env=os.environ | {"PYTHONPATH": str(folder)}, capture_output=True, text=True, timeout=120)
    assert run.returncode == 0, run.stderr
    return run.stdout.split()


def test_without_the_training_data_part(tmp_path):
    """Exactly the two folders go; ``corpus_pipeline.py`` stays where it is, and core queries run."""
    repo = tmp_path / "repo"
    shutil.copytree(ROOT, repo, ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse"))
    shutil.rmtree(repo / "skewroute" / "llm")
    shutil.rmtree(repo / "tests" / "llm", ignore_errors=True)
    assert (repo / "corpus_pipeline.py").exists()
    count, pipeline, ops, known = told(repo)
    assert int(count) > 100 and (pipeline, ops, known) == ("False", "False", "True")
    assert all(int(n) > 0 for n in told(repo, RUN))


def test_nothing_else_imports_it():
    for f in (ROOT / "skewroute").rglob("*.py"):
        if "llm" not in f.parts:
            assert "skewroute.llm" not in f.read_text() and "corpus_pipeline" not in f.read_text()


def test_entry_runs(spark):
    sys.path.insert(0, str(ROOT))
    import __spark_entry__

    rows = __spark_entry__.entry(spark).collect()
    assert len(rows) == 20 and abs(sum(r["load"] for r in rows) - 1) < 1e-9
