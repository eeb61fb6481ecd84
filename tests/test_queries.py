"""Queries against their SQL on the smallest tables: a part of each family here, all of them in the driver's run."""

import glob
import os
from collections import Counter
from decimal import Decimal

import duckdb
import pytest
from fdrepair.registry import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
PICKED = [n for n in ORACLES if n.startswith(("op_", "fn_", "udf", "udtf", "udaf", "pat_", "compose_", "errors_", "detect_", "discover_", "example_", "repair_orders_hybrid", "repair_case2", "repair_customer", "select_hybrid_line", "quality_closing", "expr_", "metric_gain", "base_", "stream_tumbling", "stream_stateful", "incremental_"))]


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for path in glob.glob(f"{SF}/*.parquet"):
        con.sql(f"create view {os.path.basename(path)[:-8]} as select * from '{path}'")
    return con


def plain(v):
    if isinstance(v, (float, Decimal)):
        return round(float(v), 6)
    return str(v) if isinstance(v, (list, dict)) else v


@pytest.mark.parametrize("name", PICKED)
def test_as_sql(spark, db, name):
    df = QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    got = Counter(tuple(plain(r[c]) for c in columns) for r in df.collect())
    want = db.sql(ORACLES[name])
    assert sorted(want.columns) == columns
    at = [want.columns.index(c) for c in columns]
    assert got == Counter(tuple(plain(r[k]) for k in at) for r in want.fetchall())


def test_registry():
    import __spark_entry__ as entry

    assert set(ORACLES) <= set(QUERIES) <= set(entry.queries())
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_import_needs_no_session():
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parents[1]
    code = "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()))"
    assert subprocess.run([sys.executable, "-c", code], cwd=root, capture_output=True).returncode == 0
