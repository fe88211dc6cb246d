"""Matrices derived from the given tables, as Spark plans and as SQL of the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semigrid.matrix import SparseMatrix
from semigrid.plans.scratch import materialize
from semigrid.sources.tables import table

#: Places of parts in the bipartite graph start here, above any order.
PART_OFFSET = 1 << 40
#: SQL in the common part of Spark's and DuckDB's dialects, each giving unique (i, j, v).
SQL: dict[str, str] = {
    "OP": "SELECT l_orderkey AS i, l_partkey AS j, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS v FROM lineitem GROUP BY l_orderkey, l_partkey",
    "PS": "SELECT l_partkey AS i, l_suppkey AS j, count(*) AS v FROM lineitem GROUP BY l_partkey, l_suppkey",
    "OS": "SELECT l_orderkey AS i, l_suppkey AS j, count(*) AS v FROM lineitem GROUP BY l_orderkey, l_suppkey",
    "CP": "SELECT o_custkey AS i, l_partkey AS j, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS v FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY o_custkey, l_partkey",
    "UH": "SELECT user_id AS i, CAST(extract(day FROM ts) * 24 + extract(hour FROM ts) - 24 AS BIGINT) AS j, count(*) AS v FROM events GROUP BY user_id, CAST(extract(day FROM ts) * 24 + extract(hour FROM ts) - 24 AS BIGINT)",
    "NR": "SELECT CAST(c_nationkey AS BIGINT) AS i, c_custkey AS j, CAST(1 AS BIGINT) AS v FROM customer",
    "RN": "SELECT CAST(n_regionkey AS BIGINT) AS i, CAST(n_nationkey AS BIGINT) AS j, CAST(1 AS BIGINT) AS v FROM nation",
    "BR": "SELECT CAST(p_size AS BIGINT) AS i, p_partkey AS j, CAST(1 AS BIGINT) AS v FROM part",
    "BW": "SELECT CAST(length(p_type) AS BIGINT) AS i, p_partkey AS j, CAST(p_size AS BIGINT) AS v FROM part",
    "SUCC": "SELECT a AS i, b AS j, count(*) AS v FROM (SELECT l_partkey AS a, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey) AS b FROM lineitem) t WHERE b IS NOT NULL AND a <> b GROUP BY a, b",
    "BIP": f"SELECT DISTINCT l_orderkey AS i, l_partkey + {PART_OFFSET} AS j, CAST(1 AS BIGINT) AS v FROM lineitem UNION ALL SELECT DISTINCT l_partkey + {PART_OFFSET} AS i, l_orderkey AS j, CAST(1 AS BIGINT) AS v FROM lineitem",
    "BG": "SELECT DISTINCT l_orderkey AS i, l_partkey + (SELECT max(l_orderkey) + 1 FROM lineitem) AS j, CAST(1 AS BIGINT) AS v FROM lineitem UNION ALL SELECT DISTINCT l_partkey + (SELECT max(l_orderkey) + 1 FROM lineitem) AS i, l_orderkey AS j, CAST(1 AS BIGINT) AS v FROM lineitem",
    "NN": "SELECT CAST(c_nationkey AS BIGINT) AS i, CAST(s_nationkey AS BIGINT) AS j, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS v FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey GROUP BY c_nationkey, s_nationkey",
}

_TABLES = {"OP": ["lineitem"], "PS": ["lineitem"], "OS": ["lineitem"], "CP": ["lineitem", "orders"], "UH": ["events"], "NR": ["customer"], "RN": ["nation"], "BR": ["part"], "BW": ["part"], "SUCC": ["lineitem"], "BIP": ["lineitem"], "BG": ["lineitem"], "NN": ["lineitem", "orders", "customer", "supplier"]}
#: Upper limits of (rows, columns) by the key columns that number them, one after the other.
_SIZES: dict[str, tuple[tuple[str, ...] | int, tuple[str, ...] | int]] = {
    "OP": (("orders", "o_orderkey"), ("part", "p_partkey")), "PS": (("part", "p_partkey"), ("supplier", "s_suppkey")), "OS": (("orders", "o_orderkey"), ("supplier", "s_suppkey")),
    "CP": (("customer", "c_custkey"), ("part", "p_partkey")), "UH": (("events", "user_id"), 744), "NR": (25, ("customer", "c_custkey")), "RN": (5, 25), "BR": (51, ("part", "p_partkey")),
    "BW": (64, ("part", "p_partkey")), "SUCC": (("part", "p_partkey"), ("part", "p_partkey")), "BIP": (2 * PART_OFFSET, 2 * PART_OFFSET), "NN": (25, 25),
    "BG": (("lineitem", "l_orderkey", "l_partkey"), ("lineitem", "l_orderkey", "l_partkey")),
}

#: Columns by which tables of over ``DEALT_LEAST`` rows are dealt to tasks of about ``DEALT_ROWS`` rows before the SQL, in place of the
#: shuffle for its groups or windows: a hash table or sort of a task then fits in a page of Spark's memory, and executors' heaps stay small.
_DEALT = {"OP": ("lineitem", "l_orderkey"), "SUCC": ("lineitem", "l_orderkey")}
DEALT_LEAST, DEALT_ROWS = 1_500_000, 250_000


def run_sql(spark: SparkSession, sf_dir: str, sql: str, tables: list[str], dealt: tuple[str, str] | None = None) -> DataFrame:
    """A query over the named tables, which are passed as arguments: no view is left behind. A large table may be ``dealt`` by a column."""
    named = {f"t_{t}": table(spark, sf_dir, t) for t in tables}
    if dealt:
        name, key = dealt
        rows = named[f"t_{name}"].count()
        if rows > DEALT_LEAST:
            named[f"t_{name}"] = named[f"t_{name}"].repartition(-(-rows // DEALT_ROWS), key)
    with_views = ", ".join(f"{t} AS (SELECT * FROM {{t_{t}}})" for t in tables)
    head = f"WITH {with_views} "
    body = sql.strip()
    if body[:5].upper() == "WITH ":
        return spark.sql(head + ", " + body[5:], **named)
    return spark.sql(head + body, **named)


def _size(spark: SparkSession, sf_dir: str, limit) -> int:
    if isinstance(limit, int):
        return limit
    name, *keys = limit
    tops = table(spark, sf_dir, name).agg(*[F.max(k) for k in keys]).first()
    return sum(int(x or 0) + 1 for x in tops)


def fixture(spark: SparkSession, sf_dir: str, name: str) -> SparseMatrix:
    """One of the derived matrices; dimensions come from column maxima of the key tables."""
    r, c = _SIZES[name]
    return SparseMatrix(run_sql(spark, sf_dir, SQL[name], _TABLES[name], _DEALT.get(name)), _size(spark, sf_dir, r), _size(spark, sf_dir, c))


def stored(m: SparseMatrix, name: str = "fixture") -> SparseMatrix:
    """The matrix as a written table, for plans that read it more than once."""
    return m.with_df(materialize(m.df, name))
