"""Reading and writing matrices: plain tables, blocks, bucketed tables and coordinate text."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semigrid.functions.blocks import FIELDS, ColumnIndex, read_block, value_arrays
from semigrid.matrix import SparseMatrix
from semigrid.plans.multiply import StoredBlocks, relational, with_blocks
from semigrid.plans.scratch import scratch_root


def write_triples(m: SparseMatrix, path: str, fmt: str = "parquet") -> None:
    """Triples sorted by column within files, so a column's rows lie in few row groups."""
    m.df.sortWithinPartitions("j", "i").write.format(fmt).mode("overwrite").save(path)


def read_triples(spark: SparkSession, path: str, nrows: int, ncols: int, fmt: str = "parquet") -> SparseMatrix:
    return SparseMatrix(spark.read.schema("i long, j long, v long").format(fmt).load(path), nrows, ncols)


def write_blocks(m: SparseMatrix, path: str, rows: int, cols: int) -> None:
    """One folder for each nonempty block; readers of a few blocks open no others."""
    with_blocks(m, rows, cols).repartition("bi", "bj").sortWithinPartitions("bi", "bj", "j", "i").write.partitionBy("bi", "bj").mode("overwrite").parquet(path)


def read_blocks(spark: SparkSession, path: str, nrows: int, ncols: int) -> SparseMatrix:
    return SparseMatrix(spark.read.parquet(path).select("i", "j", "v"), nrows, ncols)


def write_bucketed(m: SparseMatrix, name: str, key: str = "j", buckets: int = 16) -> None:
    """A table whose joins on ``key`` need no shuffle."""
    m.df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)


def fetch_columns(blocks: StoredBlocks, ids: list[int]) -> DataFrame:
    """(i, j, v) of the listed columns of blocks in column form: only blocks that may hold one are read, and each column is found by its chunk."""
    wanted = sorted({k for k in ids if 0 <= k < blocks.ncols})
    height, width = blocks.height, blocks.width
    _, value = value_arrays(blocks.kind)
    read = blocks.df.filter(F.col("bj").isin(sorted({k // width for k in wanted}) or [-1])).select("bi", "bj", *FIELDS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, (bi, bj) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())):
                index = ColumnIndex(read_block(batch, row, 2), width)
                for k in (k for k in wanted if k // width == bj):
                    i, v = index.entries(k - bj * width)
                    yield pa.RecordBatch.from_arrays([pa.array(i + bi * height, pa.int64()), pa.array([k] * len(i), pa.int64()), pa.array(v, value)], ["i", "j", "v"])

    return read.mapInArrow(run, f"i long, j long, v {blocks.kind.simpleString()}")


def write_coordinates(m: SparseMatrix, path: str) -> None:
    """Coordinate text: a folder of files with one 1-based entry a line, and a file before them with the size line."""
    line = F.concat_ws(" ", (F.col("i") + 1).cast("string"), (F.col("j") + 1).cast("string"), F.col("v").cast("string"))
    n = m.df.count()
    m.df.sparkSession.createDataFrame([(f"{m.nrows} {m.ncols} {n}",)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/size")
    m.df.select(line.alias("value")).write.mode("overwrite").text(f"{path}/entries")


def read_coordinates(spark: SparkSession, path: str, kind: str = "long") -> SparseMatrix:
    """A matrix from coordinate text, by Spark's own reader and native functions, from wherever Spark can read.

    ``path`` is a folder that ``write_coordinates`` made, or a file whose first line after the
    comments (which begin with a per cent sign) holds the sizes and which any number of tasks
    read in splits. Lines that are no entry are an error.
    """
    split = lambda c: F.split(F.trim(c), r"\s+")
    whole = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/size")
    folder = whole.getFileSystem(spark._jsc.hadoopConfiguration()).exists(whole)
    numbered = spark.read.text(f"{path}/entries" if folder else path).withColumn("_at", F.monotonically_increasing_id())
    lines = numbered.filter(~F.col("value").startswith("%") & (F.trim("value") != ""))
    if folder:
        size = spark.read.text(f"{path}/size").first()["value"]
    else:
        head = lines.agg(F.min_by("value", "_at").alias("value"), F.min("_at").alias("at")).first()  # the first line, by its place in the file
        size, lines = head["value"], lines.filter(F.col("_at") != (-1 if head["at"] is None else head["at"]))
    nrows, ncols = (int(x) for x in (size or "0 0 0").split()[:2])
    f = split(F.col("value"))
    good = F.when(F.size(f) == 3, f).otherwise(F.raise_error(F.concat(F.lit("not an entry: "), F.col("value"))).cast("array<string>"))
    fields = lines.select(good.alias("f"))
    return SparseMatrix(fields.select((F.col("f")[0].cast("long") - 1).alias("i"), (F.col("f")[1].cast("long") - 1).alias("j"), F.col("f")[2].cast(kind).alias("v")), nrows, ncols)


def queries() -> dict:
    from semigrid.sources.fixtures import fixture

    def triples(s, d) -> DataFrame:
        import uuid

        m, path = fixture(s, d, "PS"), f"{scratch_root(s)}/triples-{uuid.uuid4().hex}"
        write_triples(m, path)
        return read_triples(s, path, m.nrows, m.ncols).df

    def bucketed(s, d) -> DataFrame:
        """The parts bought together from two tables bucketed by the inner id: their join shuffles nothing."""
        import uuid

        m, name = fixture(s, d, "OP"), f"semigrid_{uuid.uuid4().hex}"
        write_bucketed(m.T, f"{name}_a", "j")
        write_bucketed(m, f"{name}_b", "i")
        a, b = s.table(f"{name}_a"), s.table(f"{name}_b")
        return relational(SparseMatrix(a, m.ncols, m.nrows), SparseMatrix(b, m.nrows, m.ncols)).df

    def blocks(s, d) -> DataFrame:
        import uuid

        m, path = fixture(s, d, "PS"), f"{scratch_root(s)}/blocks-{uuid.uuid4().hex}"
        write_blocks(m, path, 3, 2)
        return read_blocks(s, path, m.nrows, m.ncols).df

    def coordinates(s, d) -> DataFrame:
        import uuid

        path = f"{scratch_root(s)}/coordinates-{uuid.uuid4().hex}"
        write_coordinates(fixture(s, d, "PS"), path)
        return read_coordinates(s, path).df

    def formats(s, d) -> DataFrame:
        import uuid

        m, out = fixture(s, d, "PS"), None
        for fmt in ("csv", "json", "orc"):
            path = f"{scratch_root(s)}/{fmt}-{uuid.uuid4().hex}"
            write_triples(m, path, fmt)
            part = read_triples(s, path, m.nrows, m.ncols, fmt).df.agg(F.lit(fmt).alias("fmt"), F.count(F.lit(1)).alias("n"), F.sum(F.col("v") * (F.col("i") + F.col("j"))).cast("long").alias("total"))
            out = part if out is None else out.unionByName(part)
        return out

    return {"roundtrip_triples": triples, "roundtrip_blocks": blocks, "roundtrip_coordinates": coordinates, "roundtrip_formats": formats, "product_bucketed": bucketed}


def oracle_sql() -> dict[str, str]:
    from semigrid.sources.fixtures import SQL

    ps = SQL["PS"]
    total = f"SELECT count(*) AS n, CAST(sum(v * (i + j)) AS BIGINT) AS total FROM ({ps}) t"
    op = SQL["OP"]
    together = f"SELECT a.j AS i, b.j AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM ({op}) a JOIN ({op}) b ON a.i = b.i GROUP BY 1, 2"
    return {"product_bucketed": together, "roundtrip_triples": ps, "roundtrip_blocks": ps, "roundtrip_coordinates": ps, "roundtrip_formats": f"SELECT fmt, n, total FROM ({total}) t, (VALUES ('csv'), ('json'), ('orc')) x(fmt)"}
