"""Intermediate tables in the folder that driver and executors share.

Lineage is cut by writing a table, never by a block that lives on one executor:
a lost executor then costs a re-read, not a failed job.
"""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Largest table, in bytes of its rows, that is sent to every executor.
BROADCAST_BYTES = 48 << 20

_WRITTEN: list[tuple[SparkSession, str]] = []


def scratch_root(spark: SparkSession) -> str:
    """The session's shared checkpoint folder; one of our own only in local mode without any."""
    root = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if spark.sparkContext.master.startswith("local"):
        root = "file://" + tempfile.mkdtemp(prefix="semigrid-scratch-")
        spark.sparkContext.setCheckpointDir(root)
        return spark.sparkContext.getCheckpointDir().rstrip("/")
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/semigrid_scratch"


def materialize(df: DataFrame, tag: str, by: str | None = None, group: int | None = None) -> DataFrame:
    """Write ``df`` once to the shared scratch folder, in a folder for each value of ``by``, and return a scan of it.

    ``group`` is the size in bytes of row groups, which a task holds when it writes or reads them.
    """
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/{tag}-{uuid.uuid4().hex}"
    out = df.write.option("parquet.block.size", group) if group else df.write
    (out.partitionBy(by) if by else out).parquet(path)
    _WRITTEN.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


@atexit.register
def _clean() -> None:
    for spark, path in _WRITTEN:
        with contextlib.suppress(Exception):  # the session may be gone already
            hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
            hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)


def guarded_broadcast(df: DataFrame, row_bytes: int, limit: int = BROADCAST_BYTES, rows: int | None = None) -> DataFrame:
    """``df`` with a broadcast hint if its rows, counted, fit in ``limit`` bytes; else ``df`` as it is."""
    n = df.count() if rows is None else rows
    return F.broadcast(df) if n * row_bytes <= limit else df


def text_or_empty(column: str | Column) -> Column:
    return F.coalesce(F.col(column) if isinstance(column, str) else column, F.lit(""))
