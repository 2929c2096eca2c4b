"""The driver contract, and the optional part's absence."""

import shutil
import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[1]


def test_flagship(spark):
    import __spark_entry__ as entry

    assert [tuple(r) for r in entry.entry(spark).collect()] == [(6000,)]


def test_every_sql_has_its_query():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 100


def test_works_without_the_optional_part(tmp_path):
    """In a copy without the optional folders and the pipeline, queries are there and the other tests are found."""
    skip = shutil.ignore_patterns("llm", "corpus_pipeline.py", ".git", "__pycache__", "spark-warehouse", "metastore_db", ".pytest_cache")
    copy = shutil.copytree(ROOT, tmp_path / "copy", ignore=skip)
    code = """
import sys
import __spark_entry__ as e
q, sql = e.queries(), e.oracle_sql()
assert "cobucket_count" in q and set(sql) <= set(q) and "pipeline" not in q
assert not any(n.startswith("op") and n[2].isdigit() for n in q)
assert not any(m.startswith("bucketcsr.llm") or m == "corpus_pipeline" for m in sys.modules)
"""
    subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, timeout=120)
    found = subprocess.run([sys.executable, "-m", "pytest", "--collect-only", "-q", "tests"], cwd=copy, check=True, timeout=120, capture_output=True, text=True)
    assert "test_index.py" in found.stdout and "error" not in found.stdout.lower()
