"""Queries with SQL against DuckDB on the given tables."""

import duckdb
import pytest

from proxembed.llm import queries

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_equals_its_sql(spark, name):
    db = duckdb.connect()
    for t in ("documents", "pages"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    found = queries.queries()[name](spark, SF)
    want = db.execute(queries.oracle_sql()[name])
    columns = sorted(c[0] for c in want.description)
    assert sorted(found.columns) == columns
    order = [c[0] for c in want.description]
    rows = lambda many, names: sorted(repr(tuple(r[names.index(c)] for c in columns)) for r in many)
    assert rows(found.collect(), found.columns) == rows(want.fetchall(), order)
