"""The driver contract, and that the library stands without the training-data operators."""

import shutil
import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

import __spark_entry__ as entry

ROOT = Path(__file__).resolve().parent.parent
SF = Path("/root/testdata/sf0.001")
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

needs_data = pytest.mark.skipif(not SF.exists(), reason="no test tables here")


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@needs_data
def test_flagship(spark):
    assert entry.entry(spark).select("component").distinct().count() == 150


@needs_data
@pytest.mark.parametrize("name", ["cc_min_owner_doc_line", "cc_min_owner_balanced_part_supplier", "edges_event_chain", "graph_profile", "slc_threshold_doc", "bfs_from_least"])
def test_query_equals_its_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.execute(entry.oracle_sql()[name])
    cols = sorted(c[0] for c in want.description)
    place = [[c[0] for c in want.description].index(c) for c in cols]
    rows = sorted(str([r[i] for i in place]) for r in want.fetchall())
    got = entry.queries()[name](spark, str(SF))
    assert sorted(got.columns) == cols
    assert sorted(str([r[c] for c in cols]) for r in got.collect()) == rows


def test_imports_without_the_llm_folders(tmp_path):
    shutil.copytree(ROOT, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__"))
    code = "import __spark_entry__ as e; q = e.queries(); assert not any(n.startswith('op') or n == 'pipeline' for n in q) and len(q) > 80; assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "r", check=True, timeout=120)


def test_nothing_else_imports_the_llm_package():
    for f in (ROOT / "componentry").rglob("*.py"):
        if "llm" not in f.relative_to(ROOT).parts:
            assert "componentry.llm" not in f.read_text(), f
