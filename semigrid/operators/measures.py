"""Cost, balance and structure measures; none of them makes the product."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.matrix import SparseMatrix, cut


def degrees(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """(k, da, db) for inner ids with entries on both sides."""
    da = a.df.groupBy(F.col("j").alias("k")).agg(F.count(F.lit(1)).alias("da"))
    db = b.df.groupBy(F.col("i").alias("k")).agg(F.count(F.lit(1)).alias("db"))
    return da.join(db, "k")


def flops(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    return degrees(a, b).agg(F.coalesce(F.sum(F.col("da") * F.col("db")), F.lit(0)).cast("long").alias("flops"))


def inner_stats(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """nzc of A, nzr of B, and the number ni of inner ids that both have."""
    da = a.df.select(F.col("j").alias("k")).distinct().withColumn("x", F.lit(1))
    db = b.df.select(F.col("i").alias("k")).distinct().withColumn("y", F.lit(1))
    return da.join(db, "k", "full").agg(F.count("x").alias("nzc"), F.count("y").alias("nzr"), F.count_if(F.col("x").isNotNull() & F.col("y").isNotNull()).alias("ni"))


def cell_flops(a: SparseMatrix, b: SparseMatrix, q: int) -> DataFrame:
    """(bi, bj, bk, flops): products of each output cell by inner block, all blocks being contiguous ranges."""
    da = a.df.groupBy(F.col("j").alias("k"), cut("i", a.nrows, q).alias("bi")).agg(F.count(F.lit(1)).alias("da"))
    db = b.df.groupBy(F.col("i").alias("k"), cut("j", b.ncols, q).alias("bj")).agg(F.count(F.lit(1)).alias("db"))
    return da.join(db, "k").groupBy("bi", "bj", cut("k", a.ncols, q).alias("bk")).agg(F.sum(F.col("da") * F.col("db")).cast("long").alias("flops"))


def imbalance(a: SparseMatrix, b: SparseMatrix, q: int, cells: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Greatest over mean work: of whole cells, and of each stage of the rotating schedule, in which cell (i, j) uses inner block i + j + stage."""
    cells = cell_flops(a, b, q) if cells is None else cells
    overall = cells.groupBy("bi", "bj").agg(F.sum("flops").alias("flops")).agg(F.round(F.max("flops") * q * q / F.sum("flops"), 6).alias("imbalance"))
    stage = F.pmod(F.col("bk") - F.col("bi") - F.col("bj"), F.lit(q))
    per_stage = cells.withColumn("stage", stage).groupBy("stage").agg(F.round(F.max("flops") * q * q / F.sum("flops"), 6).alias("imbalance"))
    return overall, per_stage


def sync_penalty(a: SparseMatrix, b: SparseMatrix, q: int, cells: DataFrame | None = None) -> DataFrame:
    """(overall, per_stage, async_percent, sync_percent): waiting for the slowest cell at each stage costs the mean excess of stages, without barriers the overall one."""
    overall, stages = imbalance(a, b, q, cells)
    both = overall.withColumnRenamed("imbalance", "overall").join(F.broadcast(stages.agg(F.round(F.avg("imbalance"), 6).alias("per_stage"))))
    return both.withColumns({"async_percent": F.round(100 * (F.col("overall") - 1), 3), "sync_percent": F.round(100 * (F.col("per_stage") - 1), 3)})


def accumulator_traffic(a: SparseMatrix, b: SparseMatrix, slabs: int) -> DataFrame:
    """(stage, loads, products): rows whose accumulator the staged one-dimensional method loads and unloads in each stage."""
    da = a.df.select("i", F.col("j").alias("k"))
    db = b.df.groupBy(F.col("i").alias("k")).agg(F.count(F.lit(1)).alias("db"))
    rows = da.join(db, "k").groupBy(cut("k", a.ncols, slabs).alias("stage"), "i").agg(F.sum("db").alias("n"))
    return rows.groupBy("stage").agg(F.count(F.lit(1)).alias("loads"), F.sum("n").cast("long").alias("products"))


def block_stats(m: SparseMatrix, r: int, c: int) -> DataFrame:
    """(bi, bj, nnz, nzr, nzc) of nonempty blocks."""
    blocks = m.df.groupBy(cut("i", m.nrows, r).alias("bi"), cut("j", m.ncols, c).alias("bj"))
    return blocks.agg(F.count(F.lit(1)).alias("nnz"), F.countDistinct("i").alias("nzr"), F.countDistinct("j").alias("nzc"))


def storage_words(m: SparseMatrix, q: int) -> DataFrame:
    """Words of conventional and of doubly compressed columns, over a q by q grid."""
    width = -(-m.ncols // q)
    s = block_stats(m, q, q).agg(F.sum("nnz").cast("long").alias("nnz"), F.sum("nzc").cast("long").alias("nzc"), F.count(F.lit(1)).alias("blocks"))
    return s.select(F.lit(q).cast("long").alias("q"), (F.lit(q * q * (width + 1)).cast("long") + 2 * F.col("nnz")).alias("csc_words"), (2 * F.col("nzc") + F.col("blocks") + 2 * F.col("nnz")).alias("dcsc_words"))


def hypersparsity(m: SparseMatrix, q: int) -> DataFrame:
    """Entries of a block for each of its columns, and the share of blocks with under one."""
    width = -(-m.ncols // q)
    s = block_stats(m, q, q)
    return s.agg(F.lit(q).cast("long").alias("q"), F.round(F.sum("nnz") / (q * q * width), 6).alias("ratio"), F.round((F.count_if(F.col("nnz") < width) + q * q - F.count(F.lit(1))) / (q * q), 6).alias("hyper_share"))


def kernel_op_counts(a: SparseMatrix, b: SparseMatrix, q: int) -> DataFrame:
    """Operations of both kernels over all q^3 pairs of blocks, without logarithms of single ids."""
    kw = -(-a.ncols // q)
    da = a.df.groupBy(cut("i", a.nrows, q).alias("bi"), F.col("j").alias("k")).agg(F.count(F.lit(1)).alias("da"))
    db = b.df.groupBy(F.col("i").alias("k"), cut("j", b.ncols, q).alias("bj")).agg(F.count(F.lit(1)).alias("db"))
    pairs = da.join(db, "k").groupBy("bi", "bj", cut("k", a.ncols, q).alias("bk")).agg(F.sum(F.col("da") * F.col("db")).alias("flops"), F.count(F.lit(1)).alias("ni"))
    heap = pairs.agg(F.sum("flops").cast("long").alias("flops"), F.sum(F.col("flops") * F.log2("ni")).alias("merge"))
    col = da.agg(F.count(F.lit(1)).alias("nzc"), F.sum("da").alias("na"))
    row = db.agg(F.count(F.lit(1)).alias("nzr"), F.sum("db").alias("nb"))
    one = heap.join(F.broadcast(col)).join(F.broadcast(row))
    return one.select(
        F.lit(q).cast("long").alias("q"),
        "flops",
        (F.lit(q * q * q * kw).cast("long") + q * (F.col("na") + F.col("nb")) + F.col("flops")).cast("long").alias("classical_ops"),
        F.round(q * (F.col("nzc") + F.col("nzr")) + F.col("merge"), 0).cast("long").alias("heap_ops"),
    )


def worker_volume(a: SparseMatrix, b: SparseMatrix, q: int) -> DataFrame:
    """(bi, bj, entries) that each worker of a q by q grid receives: its row of A's blocks and its column of B's, without its own."""
    blocks = lambda m: m.df.groupBy(cut("i", m.nrows, q).alias("bi"), cut("j", m.ncols, q).alias("bj")).agg(F.count(F.lit(1)).alias("n"))
    x, y = blocks(a), blocks(b)
    spark = a.df.sparkSession
    every = spark.range(q).withColumnRenamed("id", "bi").join(F.broadcast(spark.range(q).withColumnRenamed("id", "bj")))
    row, col = x.groupBy("bi").agg(F.sum("n").alias("row")), y.groupBy("bj").agg(F.sum("n").alias("col"))
    own = every.join(row, "bi", "left").join(col, "bj", "left").join(x.withColumnRenamed("n", "x"), ["bi", "bj"], "left").join(y.withColumnRenamed("n", "y"), ["bi", "bj"], "left").fillna(0)
    return own.select("bi", "bj", (F.col("row") - F.col("x") + F.col("col") - F.col("y")).cast("long").alias("entries"))


def comm_volume(a: SparseMatrix, b: SparseMatrix, p: int, q: int) -> DataFrame:
    """(method, messages, entries, most, skew): what is received in all and by the busiest worker, and the latter over the mean.

    The one-dimensional method on p workers sends every slab of B to all others; both
    two-dimensional ones on q by q workers bring a worker its row of blocks and its column.
    """
    slabs = b.df.groupBy(cut("i", b.nrows, p).alias("s")).agg(F.count(F.lit(1)).alias("n"))
    total = b.df.agg(F.count(F.lit(1)).alias("t"))
    spark = a.df.sparkSession
    one = spark.range(p).withColumnRenamed("id", "s").join(slabs, "s", "left").fillna(0, ["n"]).join(F.broadcast(total)).select((F.col("t") - F.col("n")).alias("entries"))
    grid = worker_volume(a, b, q).select("entries")
    rows = [("block_row", one, p, p * (p - 1)), ("rotating_grid", grid, q * q, 2 * q * q * (q - 1)), ("panel_grid", grid, q * q, 2 * q * q * (q - 1))]
    out = None
    for method, df, workers, messages in rows:
        row = df.agg(F.lit(method).alias("method"), F.lit(messages).cast("long").alias("messages"), F.sum("entries").cast("long").alias("entries"), F.max("entries").cast("long").alias("most"), F.round(F.max("entries") * workers / F.sum("entries"), 6).alias("skew"))
        out = row if out is None else out.unionByName(row)
    return out
