"""Operators that SQL can express give DuckDB's rows on the smallest tables."""

import glob
import os

import duckdb
import pytest

from rotahash.llm.queries import ORACLE_SQL, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_query_equals_sql(spark, tiny, name):
    duck = duckdb.connect()
    for f in glob.glob(f"{tiny}/*.parquet"):
        duck.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    df = QUERIES[name](spark, tiny)
    columns = sorted(df.columns)
    result = duck.execute(ORACLE_SQL[name])
    names = [x[0] for x in result.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    norm = lambda v: f"{v:.6f}" if isinstance(v, float) else str(v)
    mine = sorted(tuple(norm(v) for v in row) for row in df.select(*columns).collect())
    assert mine == sorted(tuple(norm(row[i]) for i in at) for row in result.fetchall())
