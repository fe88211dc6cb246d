"""A sparse matrix as a DataFrame of (i, j, v) with explicit dimensions, 0-based."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semigrid.semiring import Semiring, semiring


@dataclass(frozen=True)
class SparseMatrix:
    """Unique entries (i, j, v); absent entries are the zero of whatever semiring is used.

    Cancelled entries are kept unless dropped on request.
    """

    df: DataFrame
    nrows: int
    ncols: int

    @property
    def T(self) -> SparseMatrix:  # noqa: N802
        return SparseMatrix(self.df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), self.ncols, self.nrows)

    def with_df(self, df: DataFrame) -> SparseMatrix:
        return replace(self, df=df)


def from_triples(df: DataFrame, i: Column | str, j: Column | str, v: Column | str, shape: tuple[int, int], ring: str | Semiring = "plus_times", dup: str = "combine") -> SparseMatrix:
    """Entries from any rows; repeated places are combined by the semiring, or rejected.

    Rows with a null index are rejected at run time, as are indices outside ``shape``.
    """
    column = lambda c: F.col(c) if isinstance(c, str) else c
    out = df.select(column(i).cast("long").alias("i"), column(j).cast("long").alias("j"), column(v).alias("v"))
    good = F.col("i").isNotNull() & F.col("j").isNotNull() & F.col("i").between(0, shape[0] - 1) & F.col("j").between(0, shape[1] - 1)
    out = out.withColumn("i", F.when(good, F.col("i")).otherwise(F.raise_error(F.lit("index outside the matrix")).cast("long")))
    add = semiring(ring).add(F.col("v"))
    grouped = out.groupBy("i", "j")
    if dup == "combine":
        return SparseMatrix(grouped.agg(add.alias("v")), *shape)
    checked = grouped.agg(add.alias("v"), F.count(F.lit(1)).alias("n"))
    return SparseMatrix(checked.select("i", "j", F.when(F.col("n") == 1, F.col("v")).otherwise(F.raise_error(F.lit("repeated entry")).cast("long")).alias("v")), *shape)


def cut(column: str | Column, size: int, parts: int) -> Column:
    """Which of ``parts`` contiguous ranges an id lies in; whole-number division, exact for any 64-bit id."""
    c = F.col(column) if isinstance(column, str) else column
    return F.call_function("div", c, F.lit(-(-size // parts)).cast("long"))
