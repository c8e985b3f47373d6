"""Queries whose job once was done on data of their own: Spark reads a given table for them, and DuckDB agrees."""

import duckdb
import pytest

import __spark_entry__ as entry_module

NAMES = ["advise_all", "bipartite_trade", "fn_string", "kernel_source", "similarity_all", "similarity_prefix", "tree_C1", "tree_C2", "tree_C3", "tree_D1", "tree_D2"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table_and_agrees(spark, sf_dir, name):
    out = entry_module.queries()[name](spark, sf_dir)
    assert out.inputFiles()
    con = duckdb.connect()
    for t in ("events", "lineitem", "orders", "customer", "supplier", "part"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    con.execute(entry_module.oracle_sql()[name])
    assert [c[0] for c in con.description] == out.columns
    want = con.fetchall()
    assert want and sorted(map(repr, map(tuple, out.collect()))) == sorted(map(repr, want))
