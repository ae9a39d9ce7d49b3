"""Queries against their SQL twins at the smallest scale."""

import duckdb
import pytest

from bitsort.llm import registry


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_sql(spark, sf, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    got = registry.queries()[name](spark, sf)
    answer = con.execute(registry.oracle_sql()[name])
    names = [d[0] for d in answer.description]
    cols = sorted(got.columns)
    assert sorted(names) == cols
    assert sorted(tuple(r[c] for c in cols) for r in got.collect()) == sorted(tuple(row[names.index(c)] for c in cols) for row in answer.fetchall())
