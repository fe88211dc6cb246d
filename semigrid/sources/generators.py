"""Input generators: scale-free, uniform, mesh, permutation, tall-skinny and restriction matrices."""

from __future__ import annotations

from math import gcd

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from semigrid.matrix import SparseMatrix
from semigrid.operators.structure import prefix_sum

#: Quadrant weights of the scale-free generator; they are divided by their sum.
WEIGHTS = (0.6, 0.13, 0.13, 0.13)


def thresholds(weights: tuple[float, ...]) -> list[int]:
    """Bytes at which the second, third and fourth quadrant begin, from weights divided by their sum."""
    total, run, out = sum(weights), 0, []
    for w in weights[:3]:
        run += round(256 * w / total)
        out.append(run)
    return out


def rmat(spark: SparkSession, scale: int, degree: int = 8, seed: int = 7, weights: tuple[float, ...] = WEIGHTS, ids: DataFrame | None = None) -> SparseMatrix:
    """Recursive-quadrant edges, without repeats. Bytes of a digest choose the quadrants, so any engine draws the same.

    ``ids`` (id) draw an edge each; else as many as the degree asks for.
    """
    if scale > 16:
        raise ValueError("a digest has 16 bytes; use rmat_large")
    a, b, c = thresholds(weights)
    n = 1 << scale
    byte = lambda level: F.conv(F.substring("h", 2 * level + 1, 2), 16, 10).cast("int")
    row, col = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(scale):
        row = row * 2 + F.when(byte(level) >= b, 1).otherwise(0)
        col = col * 2 + F.when((byte(level) >= a) & (byte(level) < b) | (byte(level) >= c), 1).otherwise(0)
    drawn = (spark.range(n * degree) if ids is None else ids).select(F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string"))).alias("h"))
    edges = drawn.select(row.alias("i"), col.alias("j")).distinct()
    return SparseMatrix(edges.withColumn("v", F.lit(1).cast("long")), n, n)


def rmat_sql(scale: int, degree: int = 8, seed: int = 7, weights: tuple[float, ...] = WEIGHTS, ids: str | None = None) -> str:
    a, b, c = thresholds(weights)
    byte = [f"('0x' || h[{2 * k + 1}:{2 * k + 2}])::INT" for k in range(scale)]
    row = " + ".join(f"{1 << (scale - 1 - k)} * ({x} >= {b})::BIGINT" for k, x in enumerate(byte))
    col = " + ".join(f"{1 << (scale - 1 - k)} * ({x} >= {a} AND {x} < {b} OR {x} >= {c})::BIGINT" for k, x in enumerate(byte))
    return f"SELECT DISTINCT CAST({row} AS BIGINT) AS i, CAST({col} AS BIGINT) AS j, CAST(1 AS BIGINT) AS v FROM (SELECT md5('{seed}:' || id) AS h FROM {ids or f'range({(1 << scale) * degree}) r(id)'})"


def rmat_large(spark: SparkSession, scale: int, degree: int = 8, seed: int = 7, weights: tuple[float, ...] = WEIGHTS) -> SparseMatrix:
    """The same recursion for any scale, with a cheap hash for each level."""
    a, b, c = thresholds(weights)

    def bits(which: str) -> Column:
        def step(acc: Column, level: Column) -> Column:
            x = F.pmod(F.xxhash64(F.col("id"), level, F.lit(seed)), F.lit(256))
            hit = x >= b if which == "row" else (x >= a) & (x < b) | (x >= c)
            return acc * 2 + F.when(hit, 1).otherwise(0)

        return F.aggregate(F.sequence(F.lit(1), F.lit(scale)), F.lit(0).cast("long"), step)

    n = 1 << scale
    edges = spark.range(n * degree).select(bits("row").alias("i"), bits("col").alias("j")).distinct()
    return SparseMatrix(edges.withColumn("v", F.lit(1).cast("long")), n, n)


def _digits(seed: int, modulus: int, place: int) -> Column:
    """A number below ``modulus`` from twelve digits of an id's digest; places 0 and 12 are independent."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string"))), place + 1, 12), 16, 10).cast("long") % modulus


def _digits_sql(seed: int, modulus: int, place: int) -> str:
    return f"(('0x' || md5('{seed}:' || id)[{place + 1}:{place + 12}])::BIGINT % {modulus})"


def tall_skinny(spark: SparkSession, n: int, k: int, per_column: int, seed: int = 3) -> SparseMatrix:
    """n by k: so many entries for each column are drawn, each with independent row and column, without repeats."""
    e = spark.range(k * per_column).select(_digits(seed, n, 0).alias("i"), _digits(seed, k, 12).alias("j")).distinct()
    return SparseMatrix(e.withColumn("v", F.lit(1).cast("long")), n, k)


def tall_skinny_sql(n: int, k: int, per_column: int, seed: int = 3) -> str:
    return f"SELECT DISTINCT {_digits_sql(seed, n, 0)} AS i, {_digits_sql(seed, k, 12)} AS j, CAST(1 AS BIGINT) AS v FROM range({k * per_column}) r(id)"


def erdos_renyi(spark: SparkSession, n: int, c: int, seed: int = 3) -> SparseMatrix:
    """n by n, c n places drawn uniformly and independently, without repeats."""
    return tall_skinny(spark, n, n, c, seed)


def grid3d(spark: SparkSession, m: int, ids: DataFrame | None = None) -> SparseMatrix:
    """Seven-point mesh of m^3 vertices, or of those that ``ids`` (id) names, loops included."""
    steps = [(0, 0, 0), (1, 0, 0), (-1, 0, 0), (0, 1, 0), (0, -1, 0), (0, 0, 1), (0, 0, -1)]
    moves = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.lit(c).alias("c")) for a, b, c in steps])
    at = (spark.range(m**3) if ids is None else ids).select("id", (F.col("id") % m).alias("x"), (F.floor(F.col("id") / m) % m).alias("y"), F.floor(F.col("id") / m**2).alias("z"), F.explode(moves).alias("s"))
    to = at.select("id", (F.col("x") + F.col("s.a")).alias("x"), (F.col("y") + F.col("s.b")).alias("y"), (F.col("z") + F.col("s.c")).alias("z"))
    ok = F.col("x").between(0, m - 1) & F.col("y").between(0, m - 1) & F.col("z").between(0, m - 1)
    edges = to.filter(ok).select(F.col("id").alias("i"), (F.col("x") + F.col("y") * m + F.col("z") * m * m).cast("long").alias("j"), F.lit(1).cast("long").alias("v"))
    return SparseMatrix(edges if ids is None else edges.join(ids.select(F.col("id").alias("j")), "j", "left_semi").select("i", "j", "v"), m**3, m**3)


def grid3d_sql(m: int) -> str:
    return f"""SELECT id AS i, x + a + (y + b) * {m} + (z + c) * {m * m} AS j, CAST(1 AS BIGINT) AS v
FROM (SELECT id, id % {m} AS x, id // {m} % {m} AS y, id // {m * m} AS z FROM range({m**3}) r(id)),
(VALUES (0,0,0),(1,0,0),(-1,0,0),(0,1,0),(0,-1,0),(0,0,1),(0,0,-1)) s(a,b,c)
WHERE x + a BETWEEN 0 AND {m - 1} AND y + b BETWEEN 0 AND {m - 1} AND z + c BETWEEN 0 AND {m - 1}"""


def permutation(spark: SparkSession, n: int, mul: int = 389, add: int = 17, ids: DataFrame | None = None) -> SparseMatrix:
    """An affine bijection of the ids below n, or of ``ids`` (id) among them: no dictionary has to be shuffled to apply it."""
    if gcd(mul, n) != 1:
        raise ValueError("multiplier and size share a factor")
    return SparseMatrix((spark.range(n) if ids is None else ids).select(F.col("id").alias("i"), ((F.col("id") * mul + add) % n).alias("j"), F.lit(1).cast("long").alias("v")), n, n)


def permutation_sql(n: int, mul: int = 389, add: int = 17) -> str:
    return f"SELECT id AS i, (id * {mul} + {add}) % {n} AS j, CAST(1 AS BIGINT) AS v FROM range({n}) r(id)"


def random_permutation(spark: SparkSession, n: int, seed: int = 1, ids: DataFrame | None = None) -> SparseMatrix:
    """A permutation drawn at random: ids in the order of their digests. ``ids`` (id) are numbered from 0 on if given.

    The order is cut by the first digits of the digests into ranges, so no task orders them all.
    """
    drawn = (spark.range(n) if ids is None else ids).withColumn("h", F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string")))).withColumn("part", F.conv(F.substring("h", 1, 3), 16, 10).cast("long"))
    sizes = prefix_sum(drawn.groupBy("part").agg(F.count(F.lit(1)).alias("n")), "part", "n", "before").select("part", "before")
    place = F.row_number().over(Window.partitionBy("part").orderBy("h", "id")) - 1
    placed = drawn.withColumn("place", place).join(F.broadcast(sizes), "part")  # 4096 rows at most
    return SparseMatrix(placed.select(F.col("id").alias("i"), (F.col("before") + F.col("place")).alias("j"), F.lit(1).cast("long").alias("v")), n, n)


def random_permutation_sql(n: int | str, seed: int = 1, ids: str | None = None) -> str:
    return f"SELECT id AS i, row_number() OVER (ORDER BY md5('{seed}:' || id), id) - 1 AS j, CAST(1 AS BIGINT) AS v FROM {ids or f'range({n}) r(id)'}"


def restriction(spark: SparkSession, n: int, order: int, mode: str = "consecutive", seed: int = 1, ids: DataFrame | None = None) -> SparseMatrix:
    """(n / order) by n with one entry a column, or for each of ``ids`` (id): ``order`` vertices become one, consecutive ones or ones drawn at random."""
    if mode == "random":
        places = random_permutation(spark, n, seed, ids).df
        rows = places.select(F.call_function("div", F.col("j"), F.lit(order).cast("long")).alias("i"), F.col("i").alias("j"), "v")
        return SparseMatrix(rows, -(-n // order), n)
    return SparseMatrix((spark.range(n) if ids is None else ids).select(F.call_function("div", F.col("id"), F.lit(order).cast("long")).alias("i"), F.col("id").alias("j"), F.lit(1).cast("long").alias("v")), -(-n // order), n)
