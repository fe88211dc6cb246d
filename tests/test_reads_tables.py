"""Queries that once made their data up read a given table in Spark's tasks, and give the rows of their SQL."""

import glob
import os

import pytest

import __spark_entry__ as entry

DATA = "/root/testdata/sf0.001"
NAMES = ["balanced_cuts", "contract_rmat_2", "contract_rmat_4", "contract_rmat_8", "dimension_bound", "gen_grid3d", "gen_permutation", "gen_random_permutation", "gen_restriction", "gen_restriction_random", "gen_rmat"]


@pytest.mark.skipif(not os.path.isdir(DATA), reason="no test tables here")
@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table(spark, name):
    import duckdb

    con = duckdb.connect()
    for f in glob.glob(f"{DATA}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    got = entry.queries()[name](spark, DATA)
    want = con.sql(f"SELECT {', '.join(got.columns)} FROM ({entry.oracle_sql()[name]}) q").fetchall()
    assert sorted(map(repr, map(tuple, got.collect()))) == sorted(map(repr, want))
    assert "parquet" in got._jdf.queryExecution().executedPlan().toString()
