"""Queries that made their data up read a given table."""

import duckdb
import pytest

from private_traces.plans import catalog


@pytest.mark.parametrize("name, table", [("budget_ledger", "lineitem"), ("noise_geometric", "orders"), ("noise_laplace", "orders"), ("random_regions", "lineitem")])
def test_a_table_is_read_and_sql_agrees(spark, sf, name, table):
    found = catalog.QUERIES[name](spark, sf)
    assert any(f.endswith(f"{table}.parquet") for f in found.inputFiles())
    c = duckdb.connect()
    c.sql(f"CREATE VIEW {table} AS SELECT * FROM '{sf}/{table}.parquet'")
    want = c.sql(catalog.ORACLES[name])
    assert sorted(map(tuple, found.collect())) == sorted(want.fetchall()) and found.columns == want.columns
