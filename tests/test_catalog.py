"""Every query with SQL gives the same rows as DuckDB on the smallest tables; plans prune, push and broadcast."""

import datetime
import math
import os
from decimal import Decimal

import duckdb
import pytest

from salvage import catalog
from salvage.operators import expressions, joins

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def norm(v):
    if isinstance(v, float):
        return None if math.isnan(v) else float(f"{v:.9g}")
    if isinstance(v, Decimal):
        return float(v)
    if isinstance(v, (list, tuple)):
        return tuple(map(norm, v))
    if isinstance(v, (datetime.datetime, datetime.date)):
        return v.isoformat()
    return v


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_rows_equal_sql(spark, sf, duck, name):
    df = catalog.queries()[name](spark, sf)
    columns = sorted(df.columns)
    got = sorted((norm(tuple(r[c] for c in columns)) for r in df.collect()), key=repr)
    result = duck.execute(catalog.oracle_sql()[name])
    names = [d[0] for d in result.description]
    assert sorted(names) == columns
    assert got == sorted((norm(tuple(r[names.index(c)] for c in columns)) for r in result.fetchall()), key=repr)


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_scans_prune_and_push(spark, sf):
    text = plan(expressions.scan_pruned(spark, sf))
    assert "PushedFilters: [IsNotNull(lang)" in text and "text" not in text.split("ReadSchema:")[1]


def test_small_sides_are_broadcast(spark, sf):
    assert "BroadcastHashJoin" in plan(joins.join_broadcast(spark, sf))
    assert "CartesianProduct" not in plan(joins.join_theta(spark, sf))


def test_entry_needs_no_llm_folder(tmp_path):
    """The library and its entry point work without the subpackage for training data and without the pipeline."""
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{root}/salvage", tmp_path / "salvage", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'pipeline' not in q and not any(k.startswith('op') for k in q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-B", "-c", code], cwd=tmp_path, check=True, env={**os.environ, "PYTHONPATH": str(tmp_path)})
