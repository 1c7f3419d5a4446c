"""Operators with SQL against DuckDB on the smallest table."""

import duckdb
import pytest

from influence_engine.llm import registry

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(registry.ORACLE_SQL))
def test_same_rows(spark, name):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    df, rel = registry.QUERIES[name](spark, SF), con.sql(registry.ORACLE_SQL[name])
    names = sorted(rel.columns)
    assert names == sorted(df.columns)
    assert sorted(df.select(names).collect()) == sorted(rel.select(*names).fetchall())
