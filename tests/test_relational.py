"""Joins within large groups meet ranges of ids, and give the rows of their SQL across the borders of ranges."""

import duckdb
import pytest

from semigrid.operators import relational as R


@pytest.mark.parametrize("name", ["join_range", "join_self"])
def test_ranges_of_ids(spark, tmp_path, name):
    con = duckdb.connect()
    keys = "range(-130, 400)" if name == "join_range" else f"range({R.SELF_IDS - 60}, {R.SELF_IDS + 60})"
    table, columns = {"join_range": ("part", "id AS p_partkey, CAST(id % 3 AS INT) AS p_size"), "join_self": ("customer", "id AS c_custkey, CAST(id % 2 AS INT) AS c_nationkey, CASE WHEN id % 7 = 0 THEN NULL ELSE 'x' END AS c_mktsegment")}[name]
    con.sql(f"COPY (SELECT {columns} FROM {keys} r(id)) TO '{tmp_path}/{table}.parquet'")
    con.sql(f"CREATE VIEW {table} AS FROM '{tmp_path}/{table}.parquet'")
    got = R.queries()[name](spark, str(tmp_path))
    assert sorted(map(tuple, got.collect())) == sorted(con.sql(R.oracle_sql()[name]).fetchall())
    hashed = [line for line in got._jdf.queryExecution().executedPlan().toString().split("\n") if "ShuffledHashJoin" in line]
    assert hashed and all("FLOOR" in line or "r#" in line for line in hashed), "ranges are among the keys of the join"
