"""Connected components by alternating star contractions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.plans.scratch import materialize

#: Edges that a task contracts together.
HELD_EDGES = 500_000


def local_stars(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node of its component) of the given edges alone, without the least nodes themselves."""
    ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(ids))
    while True:
        x, y = root[a], root[b]
        if (x == y).all():
            break
        least = np.minimum(x, y)
        np.minimum.at(root, x, least)
        np.minimum.at(root, y, least)
        while (root[root] != root).any():
            root = root[root]
    hung = root != np.arange(len(ids))
    return ids[hung], ids[root[hung]]


def _contracted(edges: DataFrame) -> DataFrame:
    """Each task replaces the edges it reads, so many at a time, by stars that connect the same nodes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def stars() -> pa.RecordBatch:
            table = pa.Table.from_batches(held)
            found = local_stars(table.column(0).to_numpy(), table.column(1).to_numpy())
            return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in found], ["u", "v"])

        for batch in batches:
            held.append(batch)
            if sum(b.num_rows for b in held) >= HELD_EDGES:
                yield stars()
                held = []
        if held:
            yield stars()

    return edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).mapInArrow(run, "u long, v long")


def _edges(df: DataFrame) -> DataFrame:
    return df.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()


def _large_star(edges: DataFrame) -> DataFrame:
    """Every larger neighbour of a vertex is hung on the least vertex in its neighbourhood."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    return _edges(both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")))


def _small_star(edges: DataFrame) -> DataFrame:
    """Every smaller neighbour of a vertex, and the vertex, is hung on the least of them."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    hung = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return _edges(hung.unionByName(least.select("u", F.col("m").alias("v"))))


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for each vertex that is not the least of its component.

    ``edges`` has columns u and v; loops and repeats are allowed, nulls are not. Tasks first
    contract what they hold; rounds of a large and a small star then double the reach, so
    there are about log2 of the diameter of what is left. Minima are combined before the
    shuffle, so a hub costs one row per task. Each round is a table in the shared scratch
    folder, and only its size and checksum come to the driver. The rounds end when
    nothing changes; if that takes more than ``max_rounds``, it is an error.
    """

    def signed(df: DataFrame) -> tuple[DataFrame, tuple]:
        now = materialize(df, "edges")
        return now, tuple(now.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first())

    now, sign = signed(_contracted(_edges(edges)))
    for _ in range(max_rounds):
        now, new = signed(_contracted(_small_star(_large_star(now))))
        if new == sign:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        sign = new
    raise RuntimeError("components did not settle")
