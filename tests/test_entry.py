"""The registered queries give the rows of their SQL, on the smallest tables."""

import glob
import os

import pytest

import __spark_entry__ as entry

DATA = "/root/testdata/sf0.001"
NAMES = ["copurchase", "dcsc_columns", "dcsc_aux", "product_fused", "kernel_heap", "imbalance_stage", "bfs_path_counts", "apsp_recursive", "cfl_tags", "contract_4", "join_asof", "agg_cube", "stream_user_hours", "stream_product", "reachability_k", "product_permutation", "roundtrip_blocks", "gen_rmat"]


@pytest.mark.skipif(not os.path.isdir(DATA), reason="no test tables here")
@pytest.mark.parametrize("name", NAMES)
def test_rows_equal_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for f in glob.glob(f"{DATA}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    got = entry.queries()[name](spark, DATA)
    want = con.sql(f"SELECT {', '.join(got.columns)} FROM ({entry.oracle_sql()[name]}) q").fetchall()
    assert sorted(map(repr, map(tuple, got.collect()))) == sorted(map(repr, want))


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.skipif(not os.path.isdir(DATA), reason="no test tables here")
def test_plans(spark):
    plan = entry.entry(spark)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint,l_quantity:double>" in plan
