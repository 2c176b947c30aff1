"""Every query with SQL gives DuckDB's rows on the smallest tables."""

import glob
import os

import duckdb
import numpy as np
import pytest

from rotahash import registry

QUERIES, SQL = registry.queries(), registry.oracle_sql()


@pytest.fixture(scope="module")
def duck(tiny):
    c = duckdb.connect()
    for f in glob.glob(f"{tiny}/*.parquet"):
        c.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return c


def norm(v):
    if v is None or (isinstance(v, float) and np.isnan(v)):
        return "null"
    return f"{v:.6f}" if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, tiny, duck, name):
    df = QUERIES[name](spark, tiny)
    columns = sorted(df.columns)
    result = duck.execute(SQL[name])
    names = [x[0] for x in result.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    mine = sorted(tuple(norm(v) for v in row) for row in df.select(*columns).collect())
    theirs = sorted(tuple(norm(row[i]) for i in at) for row in result.fetchall())
    assert mine == theirs


def test_sql_names_are_queries():
    assert set(SQL) <= set(QUERIES)


@pytest.mark.parametrize("name", ["bin_split", "bin_minima_partial_final"])
def test_ids_beyond_the_universe(spark, tmp_path, name):
    rows = [(1 << 14, "a b"), (70_000, "b c"), (3, "a"), (None, "a")]
    spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, 5), (1, 40_000), (2, 90_000)], "l_suppkey long, l_partkey long").coalesce(1).write.parquet(str(tmp_path / "lineitem.parquet"))
    spark.createDataFrame([(90_000,)], "p_partkey long").coalesce(1).write.parquet(str(tmp_path / "part.parquet"))
    c = duckdb.connect()
    for t in ("documents", "lineitem", "part"):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'" + (" WHERE doc_id IS NOT NULL" if t == "documents" else ""))
    df = QUERIES[name](spark, str(tmp_path))
    columns = ", ".join(df.columns)
    mine = sorted(tuple(map(norm, r)) for r in df.collect())
    assert mine == sorted(tuple(map(norm, r)) for r in c.execute(f"SELECT {columns} FROM ({SQL[name]})").fetchall()) and mine


@pytest.mark.parametrize("name", ["bin_offset_map", "clockwise_fill", "copy_clockwise_sig", "copy_offset_sig", "copy_two_way_sig", "copy_uniform_baskets_sig", "donor_profile", "empty_bin_profile", "empty_slots_anti"])
def test_universe_is_that_of_the_baskets(spark, tmp_path, name):
    """Parts that no basket holds change nothing; an id that part lacks stays in its basket."""
    lines = [(1, 5, 1), (1, 20_000, 1), (2, 32_767, 1), (3, None, 1), (4, 17, 1), (4, 17, 1)]
    for folder, rows, top in (("more", lines, 90_000), ("less", [*lines, (5, 40_000, 1)], 32_767)):
        spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_suppkey long").coalesce(1).write.parquet(str(tmp_path / folder / "lineitem.parquet"))
        spark.createDataFrame([(top,)], "p_partkey long").coalesce(1).write.parquet(str(tmp_path / folder / "part.parquet"))
    df = QUERIES[name](spark, str(tmp_path / "more"))
    c = duckdb.connect()
    c.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/more/lineitem.parquet/*.parquet'")
    columns = ", ".join(df.columns)
    mine = sorted(tuple(map(norm, r)) for r in df.collect())
    assert mine == sorted(tuple(map(norm, r)) for r in c.execute(f"SELECT {columns} FROM ({SQL[name]})").fetchall()) and mine
    whole = QUERIES[name](spark, str(tmp_path / "less"))
    if name == "empty_bin_profile":
        assert whole.agg({"sets": "sum"}).first()[0] == 4
    else:
        assert sorted(r[0] for r in whole.select("set_id").distinct().collect()) == [1, 2, 4, 5]


@pytest.mark.parametrize(("name", "table"), [("math_mod_bits", "events"), ("decimal_and_cast", "orders"), ("lateral_probe", "customer"), ("donor_first_attempt", "customer"), ("empty_bins_law", "lineitem"), ("mse_contiguous_ids", "supplier"), ("mse_synthetic_fig3", "customer"), ("mse_synthetic_fig3_k128", "customer"), ("mse_synthetic_fig3_m_2k", "customer"), ("mse_synthetic_grid_d1024", "supplier")])
def test_rows_come_from_a_table(spark, tiny, name, table):
    assert [os.path.basename(f) for f in QUERIES[name](spark, tiny).inputFiles()] == [f"{table}.parquet"]
