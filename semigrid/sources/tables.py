"""Scans of the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Parquet scan of one table; columns and filters reach the scan through Catalyst."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
