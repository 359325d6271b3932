"""The text operators' queries against their SQL twins, columns included."""

import duckdb
import pytest

from warpspan.llm import queries


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_rows_and_columns_are_the_twins(spark, sf, name):
    db = duckdb.connect()
    for table in ("documents", "benchmark"):
        db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{sf}/{table}.parquet'")
    twin = db.execute(queries.oracle_sql()[name])
    found = queries.queries()[name](spark, sf)
    assert found.columns == [c[0] for c in twin.description]
    assert sorted(map(tuple, found.collect()), key=repr) == sorted(twin.fetchall(), key=repr)
