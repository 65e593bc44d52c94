"""Measures that were constants are taken from the given tables, and equal their SQL."""

import duckdb
import pytest

from labelflow import surface_queries  # noqa: F401  registers
from labelflow.registry import QUERIES, SQL

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["capacity_formula", "method_matrix", "schema_checks"])
def test_the_query_reads_a_table_and_equals_its_sql(spark, name):
    db = duckdb.connect()
    for t in ("orders", "lineitem", "events"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = QUERIES[name](spark, SF)
    want = db.execute(SQL[name])
    assert [c[0] for c in want.description] == got.columns
    assert sorted(map(tuple, got.collect())) == sorted(want.fetchall())
    assert any("orders" in f or "lineitem" in f for f in got.inputFiles())
