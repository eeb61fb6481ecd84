"""Exact references, worked qualities and the recursion run on given tables."""

import pytest
from test_queries import ORACLES, QUERIES, SF, db, plain  # noqa: F401


@pytest.mark.parametrize("name, table", [("exact_minimal", "lineitem"), ("exact_pattern_preserving", "lineitem"), ("exact_knapsack", "lineitem"), ("example_tour_quality", "orders"), ("example_tour_rank_quality", "orders"), ("op_cte_recursive", "orders")])
def test_reads_a_given_table(spark, db, name, table):  # noqa: F811
    assert f"from {table}" in ORACLES[name]
    df = QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted(tuple(plain(r[c]) for c in columns) for r in df.collect())
    want = db.sql(ORACLES[name])
    at = [want.columns.index(c) for c in columns]
    assert got and got == sorted(tuple(plain(r[k]) for k in at) for r in want.fetchall())
