"""Table functions for SQL: unpacking compressed blocks, and drawing edges."""

from __future__ import annotations

from hashlib import md5

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from semigrid.sources.generators import WEIGHTS, thresholds

#: Taken along by value, as the functions are.
_BOUNDS = tuple(thresholds(WEIGHTS))


@udtf(returnType="i: long, j: long, v: long")
class DcscUnpack:
    """Entries of one doubly compressed block given as arrays of column ids, pointers, rows and values."""

    def eval(self, jc: list, cp: list, ir: list, num: list):
        for k, j in enumerate(jc):
            for p in range(cp[k], cp[k + 1]):
                yield ir[p], j, num[p]


@udtf(returnType="i: long, j: long")
class RmatEdges:
    """Edges that the ids from ``low`` up to ``high`` draw in the scale-free generator; repeats are not removed."""

    def eval(self, low: int, high: int, scale: int, seed: int):
        a, b, c = _BOUNDS
        for k in range(low, high):
            digest, i, j = md5(f"{seed}:{k}".encode()).digest(), 0, 0
            for x in digest[:scale]:
                i, j = 2 * i + (x >= b), 2 * j + (a <= x < b or x >= c)
            yield i, j


def register(spark: SparkSession) -> None:
    """Adds ``dcsc_unpack(ids, start, minor, num)`` and ``rmat_edges(low, high, scale, seed)`` to SQL."""
    spark.udtf.register("dcsc_unpack", DcscUnpack)
    spark.udtf.register("rmat_edges", RmatEdges)


def rmat_by_function(spark: SparkSession, scale: int, degree: int = 8, seed: int = 7, step: int = 1024):
    """The generator's edges in SQL, a range of ids for each call."""
    register(spark)
    total = (1 << scale) * degree
    return spark.sql(
        f"SELECT DISTINCT e.i, e.j, CAST(1 AS BIGINT) AS v FROM (SELECT id AS low, least(id + {step}, {total}) AS high FROM range(0, {total}, {step})) r, "
        f"LATERAL rmat_edges(r.low, r.high, {scale}, {seed}) e"
    )
