"""Structural operators on triples and the columns of compressed formats."""

from __future__ import annotations

from math import gcd

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from semigrid.matrix import SparseMatrix
from semigrid.semiring import semiring


def prefix_sum(df: DataFrame, key: str, value: str, out: str, width: int = 4096, levels: int = 4) -> DataFrame:
    """Sum of ``value`` over smaller keys, which are unique.

    Ranges of keys are summed within themselves, and their totals in the same way, so a
    window holds ``width`` rows at most; after the last level there are so few totals
    left, for any 64-bit keys in use, that one task adds them.
    """
    part = F.call_function("div", F.col(key), F.lit(width).cast("long"))
    totals = df.groupBy(part.alias("_p")).agg(F.sum(value).alias("_t"))
    if levels > 1:
        before = prefix_sum(totals, "_p", "_t", "_b", width, levels - 1).select("_p", "_b")
    else:
        before = totals.withColumn("_b", F.coalesce(F.sum("_t").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("_p", "_b")
    own = key if key != "_p" else "_k"
    with_part = df.withColumnRenamed(key, own).withColumn("_p", F.call_function("div", F.col(own), F.lit(width).cast("long")))
    with_part = with_part.withColumn("_i", F.coalesce(F.sum(value).over(Window.partitionBy("_p").orderBy(own).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    summed = with_part.join(before.withColumnRenamed("_b", "_above"), "_p").withColumn("_sum", (F.col("_above") + F.col("_i")).cast("long")).drop("_p", "_above", "_i")
    return summed.withColumnRenamed(own, key).withColumnRenamed("_sum", out)


def column_pointers(m: SparseMatrix) -> DataFrame:
    """(j, ptr): conventional pointers, one for each column and one for the end, empty or not."""
    counts = m.df.groupBy("j").agg(F.count(F.lit(1)).alias("n"))
    every = m.df.sparkSession.range(m.ncols + 1).withColumnRenamed("id", "j").join(counts, "j", "left").fillna(0, ["n"])
    return prefix_sum(every, "j", "n", "ptr").select("j", "ptr")


def compressed_columns(m: SparseMatrix) -> DataFrame:
    """(jc, cp, n): nonempty columns with the place of their first entry; as many rows as such columns."""
    counts = m.df.groupBy(F.col("j").alias("jc")).agg(F.count(F.lit(1)).alias("n"))
    return prefix_sum(counts, "jc", "n", "cp").select("jc", "cp", "n")


def chunk_index(m: SparseMatrix) -> DataFrame:
    """(chunk, first): for each chunk of columns, how many nonempty ones lie before it."""
    counts = m.df.select("j").distinct()
    width = -(-m.ncols // max(1, counts.count()))
    each = counts.groupBy(F.floor(F.col("j") / width).alias("chunk")).agg(F.count(F.lit(1)).alias("n"))
    every = m.df.sparkSession.range(-(-m.ncols // width) + 1).withColumnRenamed("id", "chunk").join(each, "chunk", "left").fillna(0, ["n"])
    return prefix_sum(every, "chunk", "n", "first").select("chunk", "first")


def compressed_entries(m: SparseMatrix) -> tuple[DataFrame, DataFrame]:
    """Conventional columns, encoded: pointers (j, ptr), and entries (pos, i, v) in column order, numbered through."""
    pointers = column_pointers(m)
    rank = F.row_number().over(Window.partitionBy("j").orderBy("i")) - 1
    placed = m.df.withColumn("_r", rank).join(pointers, "j").select((F.col("ptr") + F.col("_r")).alias("pos"), "i", "v")
    return pointers, placed


def from_compressed(pointers: DataFrame, placed: DataFrame, nrows: int, ncols: int) -> SparseMatrix:
    """The matrix of conventional columns: a column's entries stand from its pointer to the next."""
    following = pointers.select((F.col("j") - 1).alias("j"), F.col("ptr").alias("end"))
    spans = pointers.join(following, "j").filter("end > ptr")
    at = spans.select("j", F.explode(F.sequence("ptr", F.col("end") - 1)).alias("pos"))
    return SparseMatrix(placed.join(at, "pos").select("i", "j", "v"), nrows, ncols)


def columns(m: SparseMatrix, ids: list[int]) -> SparseMatrix:
    return m.with_df(m.df.filter(F.col("j").isin(ids)))


def balanced_cuts(m: SparseMatrix, parts: int) -> DataFrame:
    """(part, first, last, nnz): ranges of rows with about equal numbers of entries, a cheap substitute for partitioning the graph."""
    counts = m.df.groupBy("i").agg(F.count(F.lit(1)).alias("n"))
    total = counts.agg(F.sum("n").cast("long").alias("total"))
    placed = prefix_sum(counts, "i", "n", "before").join(F.broadcast(total))
    part = F.call_function("div", F.col("before") * parts, F.col("total"))
    return placed.groupBy(part.alias("part")).agg(F.min("i").alias("first"), F.max("i").alias("last"), F.sum("n").cast("long").alias("nnz"))


def nonempty(m: SparseMatrix) -> DataFrame:
    return m.df.select(F.lit("row").alias("axis"), F.col("i").alias("id")).distinct().unionByName(m.df.select(F.lit("column").alias("axis"), F.col("j").alias("id")).distinct())


def inner_intersection(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    return a.df.select(F.col("j").alias("id")).intersect(b.df.select(F.col("i").alias("id")))


def permute(m: SparseMatrix, mul: int, add: int, sides: str = "both") -> SparseMatrix:
    """Relabels by an affine bijection: a projection, nothing is shuffled. A multiplier that shares a factor with the size is refused."""
    for n, on in ((m.nrows, sides in ("both", "rows")), (m.ncols, sides in ("both", "columns"))):
        if on and gcd(mul, n) != 1:
            raise ValueError("multiplier and size share a factor: vertices would fall together")
    move = lambda c, n, on: ((F.col(c) * mul + add) % n).alias(c) if on else F.col(c)
    return m.with_df(m.df.select(move("i", m.nrows, sides in ("both", "rows")), move("j", m.ncols, sides in ("both", "columns")), "v"))


def permute_by(m: SparseMatrix, perm: SparseMatrix) -> SparseMatrix:
    """Relabels columns by a permutation matrix, as the product with it would."""
    p = perm.df.select(F.col("i").alias("j"), F.col("j").alias("_j"))
    return SparseMatrix(m.df.join(p, "j").select("i", F.col("_j").alias("j"), "v"), m.nrows, perm.ncols)


def permute_rows_by(m: SparseMatrix, perm: SparseMatrix) -> SparseMatrix:
    return permute_by(m.T, perm).T


def submatrix(m: SparseMatrix, rows: DataFrame, cols: DataFrame) -> SparseMatrix:
    """Entries in the listed rows and columns (old, new), renumbered."""
    r, c = rows.select(F.col("old").alias("i"), F.col("new").alias("_i")), cols.select(F.col("old").alias("j"), F.col("new").alias("_j"))
    return m.with_df(m.df.join(r, "i").join(c, "j").select(F.col("_i").alias("i"), F.col("_j").alias("j"), "v"))


def add(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times") -> SparseMatrix:
    return a.with_df(a.df.unionByName(b.df).groupBy("i", "j").agg(semiring(ring).add(F.col("v")).alias("v")))


def emult(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times") -> SparseMatrix:
    return a.with_df(a.df.join(b.df.withColumnRenamed("v", "y"), ["i", "j"]).select("i", "j", semiring(ring).mul(F.col("v"), F.col("y")).alias("v")))


def mask(a: SparseMatrix, m: SparseMatrix, keep: bool = True) -> SparseMatrix:
    return a.with_df(a.df.join(m.df.select("i", "j"), ["i", "j"], "left_semi" if keep else "left_anti"))


def reduce(m: SparseMatrix, axis: str, ring: str = "plus_times") -> DataFrame:
    """(id, v): the sum of each row (axis i) or column (axis j)."""
    return m.df.groupBy(F.col(axis).alias("id")).agg(semiring(ring).add(F.col("v")).alias("v"))


def select_entries(m: SparseMatrix, condition: Column) -> SparseMatrix:
    return m.with_df(m.df.filter(condition))


def trace(m: SparseMatrix) -> DataFrame:
    return m.df.filter("i = j").agg(F.coalesce(F.sum("v"), F.lit(0)).cast("long").alias("trace"))


def eye(spark, n: int) -> SparseMatrix:
    return SparseMatrix(spark.range(n).select(F.col("id").alias("i"), F.col("id").alias("j"), F.lit(1).cast("long").alias("v")), n, n)


def zero(spark, nrows: int, ncols: int, kind: str = "long") -> SparseMatrix:
    return SparseMatrix(spark.createDataFrame([], f"i long, j long, v {kind}"), nrows, ncols)


def diagonal(values: DataFrame, n: int) -> SparseMatrix:
    """A matrix with the values (id, v) on its diagonal: products with it scale rows or columns."""
    return SparseMatrix(values.select(F.col("id").alias("i"), F.col("id").alias("j"), "v"), n, n)


def selector(rows: DataFrame, count: int, n: int) -> SparseMatrix:
    """The ``count`` by n matrix whose product from the left takes the listed rows (old, new)."""
    return SparseMatrix(rows.select(F.col("new").alias("i"), F.col("old").alias("j"), F.lit(1).cast("long").alias("v")), count, n)
