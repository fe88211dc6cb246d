"""Relational operators around the products, in SQL that Spark and DuckDB read alike."""

from __future__ import annotations

from semigrid.sources.fixtures import run_sql
from semigrid.sources.tables import table

_L, _O, _E, _C = ["lineitem"], ["orders"], ["events"], ["customer"]
#: name: (tables, query)
SQL: dict[str, tuple[list[str], str]] = {
    "scan_pruned": (_L, "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'"),
    "filter_project": (_O, "SELECT o_orderkey, o_totalprice * 2 AS twice FROM orders WHERE o_orderstatus = 'F' AND o_totalprice BETWEEN 1000 AND 200000"),
    "predicate_mix": (["part"], "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS class FROM part WHERE p_brand LIKE 'Brand#1%' OR p_size IN (1, 2, 3) OR p_type IS NOT DISTINCT FROM NULL"),
    "join_inner": (["orders", "customer"], "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey"),
    "join_left": (["orders", "lineitem"], "SELECT o_orderkey, count(l_linenumber) AS lines FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey"),
    "join_full": (["customer", "supplier"], "SELECT coalesce(c_custkey, -1) AS c_custkey, coalesce(s_suppkey, -1) AS s_suppkey FROM customer FULL OUTER JOIN supplier ON c_custkey = s_suppkey * 3"),
    "join_semi": (["orders", "lineitem"], "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 48)"),
    "join_anti": (["orders", "lineitem"], "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)"),
    "join_theta": (["nation", "region"], "SELECT n_nationkey, r_regionkey FROM nation JOIN region ON n_regionkey < r_regionkey"),
    "join_range": (["part"], "SELECT a.p_partkey AS x, b.p_partkey AS y FROM part a JOIN part b ON a.p_size = b.p_size AND b.p_partkey > a.p_partkey AND b.p_partkey <= a.p_partkey + 50"),
    "join_star": (["lineitem", "orders", "customer", "nation"], "SELECT n_name, count(*) AS lines, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"),
    "join_self": (_C, "SELECT a.c_custkey AS x, b.c_custkey AS y FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_mktsegment = b.c_mktsegment AND a.c_custkey < b.c_custkey"),
    "join_interval": (_E, "SELECT a.event_id AS x, b.event_id AS y FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"),
    "join_asof": (_E, "SELECT event_id, coalesce(last_purchase, -1) AS last_purchase FROM (SELECT event_id, event_type, max(CASE WHEN event_type = 'purchase' THEN event_id END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_purchase FROM events) t WHERE event_type <> 'purchase'"),
    "join_lateral": (["nation", "customer"], "SELECT n_nationkey, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey) t"),
    "agg_hash": (_L, "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q FROM lineitem GROUP BY l_returnflag, l_linestatus"),
    "agg_distinct": (_L, "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag"),
    "agg_rollup": (_O, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)"),
    "agg_cube": (_O, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)"),
    "agg_grouping_sets": (["part"], "SELECT coalesce(p_brand, '-') AS p_brand, coalesce(p_size, -1) AS p_size, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_size), ())"),
    "agg_max_by": (_O, "SELECT o_custkey, max_by(o_orderkey, o_totalprice * 1000000 + o_orderkey) AS top FROM orders GROUP BY o_custkey"),
    "agg_having": (_L, "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY l_partkey HAVING count(*) > 35"),
    "agg_filtered": (_L, "SELECT l_suppkey, count(*) FILTER (WHERE l_quantity > 25) AS big, count(*) AS n FROM lineitem GROUP BY l_suppkey"),
    "win_rank": (_O, "SELECT o_orderkey, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice) AS BIGINT) AS r, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice) AS BIGINT) AS dr, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey) AS BIGINT) AS rn FROM orders"),
    "win_running": (_O, "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS n, max(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS m FROM orders"),
    "win_lag": (_E, "SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before, coalesce(lead(event_id) OVER w, -1) AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"),
    "win_range": (["part"], "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM part"),
    "win_ntile": (_C, "SELECT c_custkey, CAST(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS BIGINT) AS quarter FROM customer"),
    "win_first_last": (_E, "SELECT event_id, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS f FROM events"),
    "topk_global": (_O, "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20"),
    "topk_group": (_O, "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) t WHERE r <= 2"),
    "set_union": (["customer", "supplier"], "SELECT c_nationkey AS n FROM customer UNION SELECT s_nationkey FROM supplier"),
    "set_union_all": (["customer", "supplier"], "SELECT c_nationkey AS n FROM customer UNION ALL SELECT s_nationkey FROM supplier"),
    "set_intersect": (["orders", "customer"], "SELECT o_custkey AS k FROM orders INTERSECT SELECT c_custkey FROM customer"),
    "set_except": (["orders", "customer"], "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders"),
    "set_except_all": (["customer", "supplier"], "SELECT c_nationkey AS n FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier"),
    "set_intersect_all": (["customer", "supplier"], "SELECT c_nationkey AS n FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier"),
    "fn_string": (["part"], "SELECT p_partkey, upper(p_name) AS u, length(p_name) AS n, md5(p_name) AS h, replace(p_brand, '#', '-') AS b, substr(p_type, 1, 3) AS t FROM part"),
    "fn_date": (_O, "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, date_trunc('month', o_orderdate) AS t FROM orders"),
    "fn_math": (["part"], "SELECT p_partkey, round(sqrt(p_size), 6) AS s, round(log2(p_size), 6) AS l, CAST(ceil(p_size / 7.0) AS BIGINT) AS c, p_partkey % 13 AS r FROM part"),
    "subquery_scalar": (_O, "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 2 * avg(o_totalprice) FROM orders)"),
    "subquery_exists": (["customer", "orders"], "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)"),
    "cte_chain": (_L, "WITH a AS (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY l_orderkey), b AS (SELECT n, count(*) AS orders FROM a GROUP BY n) SELECT n, orders FROM b"),
    "win_tumbling": (_E, "SELECT user_id, date_trunc('hour', ts) AS w, count(*) AS n FROM events GROUP BY user_id, date_trunc('hour', ts)"),
    "win_session": (_E, "SELECT user_id, s, count(*) AS n, min(event_id) AS least FROM (SELECT user_id, event_id, CAST(sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS s FROM (SELECT user_id, event_id, ts, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events) t) u GROUP BY user_id, s"),
}


#: Ids in one range of the joins below.
RANGE_IDS, SELF_IDS = 50, 1 << 14
#: Spark's form of joins whose equal keys alone leave groups that are too large: both sides are cut in ranges of ids as well.
PLANS = {
    "join_range": f"SELECT /*+ SHUFFLE_HASH(b) */ a.p_partkey AS x, b.p_partkey AS y FROM (SELECT *, explode(array(floor(p_partkey / {RANGE_IDS}), floor(p_partkey / {RANGE_IDS}) + 1)) AS r FROM part) a JOIN (SELECT *, floor(p_partkey / {RANGE_IDS}) AS r FROM part) b ON a.p_size = b.p_size AND a.r = b.r AND b.p_partkey > a.p_partkey AND b.p_partkey <= a.p_partkey + 50",
    "join_self": f"SELECT /*+ SHUFFLE_HASH(b) */ a.c_custkey AS x, b.c_custkey AS y FROM (SELECT c.*, explode(sequence(floor(c_custkey / {SELF_IDS}), greatest(floor(c_custkey / {SELF_IDS}), top))) AS r FROM customer c CROSS JOIN (SELECT floor(max(c_custkey) / {SELF_IDS}) AS top FROM customer) t) a JOIN (SELECT *, floor(c_custkey / {SELF_IDS}) AS r FROM customer) b ON a.c_nationkey = b.c_nationkey AND a.c_mktsegment = b.c_mktsegment AND a.r = b.r AND a.c_custkey < b.c_custkey",
}


def queries() -> dict:
    out = {name: (lambda q: lambda s, d: run_sql(s, d, q[1], q[0]))((q[0], PLANS.get(name, q[1]))) for name, q in SQL.items()}
    from pyspark.sql import functions as F

    out["fn_array"] = lambda s, d: table(s, d, "embeddings").select("vec_id", F.size("embedding").cast("long").alias("n"), F.aggregate("embedding", F.lit(0).cast("long"), lambda a, x: a + F.round(x.cast("double") * 1000, 0).cast("long")).alias("total"))
    out["agg_pivot"] = lambda s, d: table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).select("user_id", F.coalesce("click", F.lit(0)).alias("clicks"), F.coalesce("view", F.lit(0)).alias("views"))
    out["fn_json"] = lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("parsed"))
    out["fn_map"] = lambda s, d: table(s, d, "nation").groupBy("n_regionkey").agg(F.size(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name")))).cast("long").alias("n"))
    out["agg_percentile"] = lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_quantity", F.lit(0.5)), 6).alias("median"))
    out["agg_approx"] = lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"))
    out["win_sliding"] = lambda s, d: table(s, d, "events").groupBy("event_type", F.window("ts", "2 days", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("event_type", F.col("w.start").alias("start"), "n")
    return out


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in SQL.items()} | {
        "agg_pivot": "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE event_type = 'view') AS views FROM events GROUP BY user_id",
        "fn_json": "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS parsed FROM events",
        "fn_array": "SELECT vec_id, len(embedding) AS n, CAST(list_sum([CAST(round(CAST(x AS DOUBLE) * 1000, 0) AS BIGINT) FOR x IN embedding]) AS BIGINT) AS total FROM embeddings",
        "fn_map": "SELECT n_regionkey, count(*) AS n FROM nation GROUP BY 1",
        "agg_percentile": "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS median FROM lineitem GROUP BY 1",
        "win_sliding": "SELECT event_type, date_trunc('day', ts) - (k * INTERVAL 1 DAY) AS start, count(*) AS n FROM events, (VALUES (0), (1)) x(k) GROUP BY 1, 2",
    }
