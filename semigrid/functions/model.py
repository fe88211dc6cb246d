"""Analytic cost model of the one- and two-dimensional products, as columns over (n, p)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Seconds a flop of the classical and of the hypersparse kernel, a message's latency, a byte's time.
GAMMA_CLASSICAL, GAMMA_HYPERSPARSE, ALPHA, BETA_BYTE = 293.6e-9, 19.2e-9, 2.3e-6, 1e-9


def speedups(spark: SparkSession, c: int = 4, bytes_moved: int = 24, gamma: float = GAMMA_CLASSICAL, exponents: tuple[int, ...] = (17, 20, 24), sides: tuple[int, ...] = (1, 2, 4, 8, 16, 32, 64)) -> DataFrame:
    """The times of ``times`` for n = 2^e and p = q * q, with c entries a row."""
    points = spark.createDataFrame([(1 << e, q * q, float(c)) for e in exponents for q in sides], "n long, p long, c double")
    return times(points, bytes_moved, gamma)


def times(points: DataFrame, bytes_moved: int = 24, gamma: float = GAMMA_CLASSICAL) -> DataFrame:
    """(n, p, c, w, comm1, comm2, mult, add, comp2) for rows (n, p, c): work and times of one product of matrices with c entries a row.

    One dimension: every worker fetches p - 1 blocks of B. Two: sqrt(p) steps of two
    messages. In each step a worker walks the nonempty ids of a pair of blocks and makes the
    products with a heap of the common ids; sums of step i are merged into a result i times
    as long. Columns of blocks are nonempty with probability 1, or c / sqrt(p) once p is over
    c^2; ids are common with the square of that.
    """
    beta, root = BETA_BYTE * bytes_moved, F.sqrt("p")
    n, p, c = F.col("n"), F.col("p"), F.col("c")
    one = F.lit(1.0)
    scan = 2 * F.least(one, c / root) * n  # of all sqrt(p) steps
    common = F.least(one, c * c / p) * n / root  # of one step
    products = c * c * n / p  # of all steps
    heap = F.greatest(F.log2(F.greatest(common, one)), one)
    mult = GAMMA_HYPERSPARSE * (scan + products * heap)
    factorial = F.aggregate(F.sequence(F.lit(1), root.cast("int")), F.lit(0.0), lambda s, x: s + F.log2(x.cast("double")))
    add = GAMMA_HYPERSPARSE * products / root * factorial
    return points.select(
        "n",
        "p",
        "c",
        (gamma * c * c * n).alias("w"),
        ((p - 1) * (ALPHA + beta * c * n / p)).alias("comm1"),
        (root * (2 * ALPHA + beta * 2 * c * n / p)).alias("comm2"),
        mult.alias("mult"),
        add.alias("add"),
        (mult + add).alias("comp2"),
    )


def model_1d(spark: SparkSession) -> DataFrame:
    """Speed-up with B assembled at every worker: it saturates."""
    return speedups(spark).select("n", "p", F.round(F.col("w") / (F.col("comm1") + F.col("w") / F.col("p")), 6).alias("speedup"))


def model_2d(spark: SparkSession) -> DataFrame:
    """Speed-up on the rotating grid: it keeps rising, with a slope below one."""
    return speedups(spark).select("n", "p", F.round(F.col("w") / (F.col("comm2") + F.col("comp2")), 6).alias("speedup"))


def model_panel(spark: SparkSession) -> DataFrame:
    """Speed-up of the panel grid: broadcasts along rows and columns cost a factor of lg p in communication, work is the same."""
    panel = F.col("comm2") * F.greatest(F.lit(1.0), F.log2("p"))
    return speedups(spark).select("n", "p", F.round(F.col("w") / (panel + F.col("comp2")), 6).alias("speedup"))


def model_dense_blocks(spark: SparkSession) -> DataFrame:
    """Parts of the time with many entries a row, where few workers see no empty column: p up to c^2 and beyond."""
    return speedups(spark, c=16, exponents=(20,)).select("n", "p", F.round(F.col("mult") * 1e6, 3).alias("mult_us"), F.round(F.col("add") * 1e6, 3).alias("add_us"))


def model_terms(spark: SparkSession, c: int = 4, bytes_moved: int = 24) -> DataFrame:
    """The three parts that efficiency is divided by, each over the useful work: walking and bandwidth, merging, and latency; and which is largest."""
    beta = BETA_BYTE * bytes_moved
    g, n, p = GAMMA_HYPERSPARSE, F.col("n"), F.col("p")
    work = g * c * c * n
    parts = speedups(spark, c).select(
        "n",
        "p",
        F.round((g + beta) * c * n * F.sqrt(p) / work, 6).alias("bandwidth"),
        F.round(F.log2(c * c * n / p), 6).alias("merging"),
        F.round(ALPHA * p * F.sqrt(p) / work, 6).alias("latency"),
    )
    top = F.greatest("bandwidth", "merging", "latency")
    return parts.withColumn("largest", F.when(top == F.col("bandwidth"), "bandwidth").when(top == F.col("merging"), "merging").otherwise("latency"))


def model_isoefficiency(spark: SparkSession, c: int = 4, share: float = 0.1) -> DataFrame:
    """The dimension n at which latency is ``share`` of the work, for each p: it grows as p^1.5."""
    points = spark.createDataFrame([(4**k,) for k in range(7)], "p long")
    return points.select("p", F.round(ALPHA * F.col("p") * F.sqrt("p") / (share * GAMMA_HYPERSPARSE * c * c), 4).alias("n"))


def ring_bounds(spark: SparkSession) -> DataFrame:
    """Operation bounds of products that need a ring, beside the sparse ones, at c = 8 entries a row."""
    points = spark.createDataFrame([(10,), (16, ), (20,)], "e long").select(F.pow(F.lit(2.0), "e").alias("n"))
    nnz = 8 * F.col("n")
    return points.select(F.col("n").cast("long").alias("n"), F.round(F.log2(F.pow("n", F.lit(3.0))), 6).alias("dense"), F.round(F.log2(F.pow("n", F.lit(2.38))), 6).alias("fast_dense"), F.round(F.log2(F.pow(nnz, F.lit(0.7)) * F.pow("n", F.lit(1.2)) + F.pow("n", F.lit(2.0))), 6).alias("fast_sparse"), F.round(F.log2(F.col("n") + nnz + 64 * F.col("n")), 6).alias("classical"))


def model_overlap(spark: SparkSession) -> DataFrame:
    """Speed-up when communication hides behind work, or the reverse."""
    return speedups(spark).select("n", "p", F.round(F.col("w") / F.greatest("comm2", "comp2"), 6).alias("speedup"))


def model_efficiency(spark: SparkSession) -> DataFrame:
    return speedups(spark).select("n", "p", F.round(F.col("w") / (F.col("p") * (F.col("comm2") + F.col("comp2"))), 8).alias("efficiency"))


def model_comm(spark: SparkSession) -> DataFrame:
    return speedups(spark).select("n", "p", F.round(F.col("comm1") * 1e6, 4).alias("one_d_us"), F.round(F.col("comm2") * 1e6, 4).alias("two_d_us"))


def dimension_bound(spark: SparkSession, c: int = 4) -> DataFrame:
    """Whether walking all ids of all blocks, n sqrt(p), outweighs the flops, c^2 n."""
    return speedups(spark, c).select("n", "p", (F.col("n") * F.sqrt("p") >= c * c * F.col("n")).alias("dominated"))


def reference_sql(select: str, c: int = 4, bytes_moved: int = 24, exponents: str = "(17), (20), (24)") -> str:
    """The same quantities in SQL, pair by pair of blocks and step by step, from the definitions."""
    beta, g, h = BETA_BYTE * bytes_moved, GAMMA_CLASSICAL, GAMMA_HYPERSPARSE
    return f"""WITH points AS (SELECT CAST(1 AS BIGINT) << e AS n, CAST(s * s AS BIGINT) AS p, s FROM (VALUES {exponents}) x(e), (VALUES (1), (2), (4), (8), (16), (32), (64)) y(s)),
block AS (SELECT *, CASE WHEN p > {c * c} THEN CAST({c} AS DOUBLE) / s ELSE 1.0 END AS hit, CAST({c * c} AS DOUBLE) * n / (CAST(p AS DOUBLE) * s) AS fl FROM points),
step AS (SELECT *, hit * n / s AS ids, CASE WHEN p > {c * c} THEN CAST({c * c} AS DOUBLE) / p ELSE 1.0 END * n / s AS ni FROM block),
k AS (SELECT n, p, {g!r} * {c * c} * n AS w, (p - 1) * ({ALPHA!r} + {beta!r} * {c} * n / p) AS comm1, s * ({2 * ALPHA!r} + {beta!r} * {2 * c} * n / p) AS comm2,
 {h!r} * s * (2 * ids + fl * CASE WHEN ni > 2 THEN log2(ni) ELSE 1.0 END) AS mult, {h!r} * fl * lgamma(s + 1) / ln(2) AS add FROM step),
m AS (SELECT *, mult + add AS comp2 FROM k)
SELECT {select} FROM m"""


_WORK = f"({GAMMA_HYPERSPARSE!r} * 16 * n)"
_TERMS = f"SELECT n, p, round(({GAMMA_HYPERSPARSE!r} + {BETA_BYTE * 24!r}) * 4 * n * sqrt(p) / {_WORK}, 6) AS bandwidth, round(log2(16.0 * n / p), 6) AS merging, round({ALPHA!r} * p * sqrt(p) / {_WORK}, 6) AS latency FROM ({reference_sql('n, p')}) m"
SQL = {
    "model_1d": reference_sql("n, p, round(w / (comm1 + w / p), 6) AS speedup"),
    "model_2d": reference_sql("n, p, round(w / (comm2 + comp2), 6) AS speedup"),
    "model_panel": reference_sql("n, p, round(w / (comm2 * greatest(1.0, log2(p)) + comp2), 6) AS speedup"),
    "model_overlap": reference_sql("n, p, round(w / greatest(comm2, comp2), 6) AS speedup"),
    "model_efficiency": reference_sql("n, p, round(w / (p * (comm2 + comp2)), 8) AS efficiency"),
    "model_comm": reference_sql("n, p, round(comm1 * 1e6, 4) AS one_d_us, round(comm2 * 1e6, 4) AS two_d_us"),
    "model_dense_blocks": reference_sql("n, p, round(mult * 1e6, 3) AS mult_us, round(add * 1e6, 3) AS add_us", 16, 24, "(20)"),
    "model_terms": f"SELECT *, CASE WHEN bandwidth >= merging AND bandwidth >= latency THEN 'bandwidth' WHEN merging >= latency THEN 'merging' ELSE 'latency' END AS largest FROM ({_TERMS}) t",
    "model_isoefficiency": f"SELECT p, round({ALPHA!r} * p ** 1.5 / ({0.1 * GAMMA_HYPERSPARSE * 16!r}), 4) AS n FROM (SELECT CAST(power(4, k) AS BIGINT) AS p FROM range(7) r(k)) t",
    "ring_bounds": "SELECT n, round(3 * log2(n), 6) AS dense, round(2.38 * log2(n), 6) AS fast_dense, round(log2((8.0 * n) ** 0.7 * n ** 1.2 + CAST(n AS DOUBLE) * n), 6) AS fast_sparse, round(log2(73.0 * n), 6) AS classical FROM (VALUES (CAST(1024 AS BIGINT)), (65536), (1048576)) t(n)",
    "dimension_bound": reference_sql("n, p, n * sqrt(p) >= 16 * n AS dominated"),
}


def calibrate(operations: list[float], seconds: list[float]) -> float:
    """Seconds an operation by least squares through the origin."""
    return sum(o * s for o, s in zip(operations, seconds)) / sum(o * o for o in operations)
