"""The driver's contract: names match, and the entry imports without the pipeline operators."""

import os
import shutil
import subprocess
import sys

import __spark_entry__ as entry

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(entry.queries()) > 150


def test_entry_runs(spark):
    assert entry.entry(spark).count() > 0


def test_entry_imports_without_the_pipeline_operators(tmp_path):
    shutil.copytree(f"{ROOT}/talkdigest", tmp_path / "talkdigest", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{ROOT}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; assert len(e.queries()) > 150 and not any(n.startswith('op1_') for n in e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env={**os.environ, "PYTHONPATH": str(tmp_path)}, check=True)


def test_pivot_scores_reads_a_given_table(spark, tmp_path):
    rows = [("A", 1.0, 0.1, 0.0), ("A", 4.0, 0.2, 0.5), ("N", 7.0, None, 0.25)]
    spark.createDataFrame(rows, "l_returnflag string, l_quantity double, l_discount double, l_tax double").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = entry.queries()["pivot_scores"](spark, str(tmp_path))
    assert got.inputFiles() and {tuple(r) for r in got.collect()} == {("A", 2.5, 0.15, 0.25), ("N", 7.0, None, 0.25)}


def test_no_query_of_fixed_values_only():
    assert "published_scores" not in entry.queries()
