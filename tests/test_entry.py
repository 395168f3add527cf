"""The driver contract."""

from __future__ import annotations

import os
import subprocess
import sys
from pathlib import Path

import __spark_entry__ as entry
from stratastore import catalogue

ROOT = Path(__file__).resolve().parent.parent


def test_entry_runs(spark):
    assert entry.entry(spark).count() == 5


def test_names():
    queries = entry.queries()
    assert set(catalogue.queries()) <= set(queries) and set(entry.oracle_sql()) <= set(queries)


def test_import_needs_no_session_and_no_optional_parts(tmp_path):
    for name in ("__spark_entry__.py", "stratastore"):
        subprocess.run(["cp", "-r", str(ROOT / name), str(tmp_path)], check=True)
    subprocess.run(["rm", "-rf", str(tmp_path / "stratastore/llm")], check=True)
    code = "import __spark_entry__ as e; assert not e.HAS_LLM and len(e.queries()) > 100; e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PYTHONPATH": str(tmp_path), "PATH": "/usr/bin:/bin"})
    # and a query with Python workers runs there
    code = "import __spark_entry__ as e; from pyspark.sql import SparkSession as S; s = S.builder.master('local[2]').config('spark.ui.enabled', 'false').config('spark.sql.shuffle.partitions', '2').getOrCreate(); assert e.entry(s).count() == 5; s.stop()"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env=os.environ | {"PYTHONPATH": str(tmp_path)}, timeout=300)


def test_small_queries_run(spark, sf):
    for name in ("tree_height", "storage_cost", "roundtrip_documents", "gc_sweep", "cumulative_cost", "wl_passage_overlap"):
        assert entry.queries()[name](spark, sf).count() > 0
