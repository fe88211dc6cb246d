"""Tiles give the rows of the SQL over many slabs, dense and listed ids, and shuffle no products."""

import glob
import os

import pytest

import __spark_entry__ as entry
from semigrid.plans import tiles

DATA = "/root/testdata/sf0.001"


@pytest.mark.skipif(not os.path.isdir(DATA), reason="no test tables here")
@pytest.mark.parametrize("name", ["cosine_topk", "user_hour_overlap", "doc_overlap_topk"])
def test_tiles(spark, monkeypatch, name):
    import duckdb

    for limit, value in (("SLAB_ROWS", 11), ("HELD_SLABS", 2), ("LIST_PRODUCTS", 100), ("DENSE_SHARE", 4)):
        monkeypatch.setattr(tiles, limit, value)
    con = duckdb.connect()
    for f in glob.glob(f"{DATA}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    got = entry.queries()[name](spark, DATA)
    want = con.sql(f"SELECT {', '.join(got.columns)} FROM ({entry.oracle_sql()[name]}) q").fetchall()
    assert sorted(map(repr, map(tuple, got.collect()))) == sorted(map(repr, want))
    assert "Join" not in got._jdf.queryExecution().executedPlan().toString()
