"""Every query with SQL against DuckDB, and the library without the training-data subpackage."""

import glob
import math
import os
import shutil
import subprocess
import sys

import duckdb
import pytest

import __spark_entry__ as entry
from rowgraph.queries import ORACLE, QUERIES

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def same(v):
    if isinstance(v, float):
        return None if math.isnan(v) else float(f"{v:.9g}")
    return v.isoformat() if hasattr(v, "isoformat") else v


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    return con


@pytest.mark.parametrize("name", sorted(ORACLE))
def test_query_equals_sql(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted((tuple(same(v) for v in r) for r in df.select(*cols).collect()), key=repr)
    found = duck.sql(ORACLE[name])
    at = [found.columns.index(c) for c in cols]
    assert len(found.columns) == len(cols)
    assert got == sorted((tuple(same(r[i]) for i in at) for r in found.fetchall()), key=repr)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLE) - {"train_planted", "train_planted_value", "compare_churn", "compare_value", "compare_attention"}))
def test_other_queries_run(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_the_rest_stands_without_the_training_data_subpackage(tmp_path):
    for f in ("rowgraph", "__spark_entry__.py"):
        src = os.path.join(ROOT, f)
        (shutil.copytree if os.path.isdir(src) else shutil.copy)(src, tmp_path / f)
    shutil.rmtree(tmp_path / "rowgraph" / "llm", ignore_errors=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'customer_churn' in q and not [k for k in q if k.startswith('op') or k == 'pipeline']; e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={**os.environ, "PYTHONPATH": str(tmp_path)})


def test_nothing_else_imports_it():
    found = subprocess.run(["grep", "-rlE", r"rowgraph\.llm|from \.+llm|import llm", "rowgraph", "--include=*.py"], cwd=ROOT, capture_output=True, text=True).stdout.split()
    assert all(f.startswith("rowgraph/llm/") for f in found)
