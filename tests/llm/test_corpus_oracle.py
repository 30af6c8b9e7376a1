"""The corpus operators that have SQL against DuckDB."""

import duckdb
import pytest

from taskmap.llm.registry import QUERIES, SQL


@pytest.mark.parametrize("name", sorted(SQL))
def test_query(spark, tiny, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tiny}/documents.parquet'")
    got = QUERIES[name](spark, tiny)
    columns = sorted(got.columns)
    told = con.execute(SQL[name])
    names = [d[0] for d in told.description]
    assert sorted(names) == columns
    want = [tuple(r[names.index(c)] for c in columns) for r in told.fetchall()]
    assert sorted((tuple(r[c] for c in columns) for r in got.collect()), key=repr) == sorted(want, key=repr)
