"""Timed experiments: kernels, strong and weak scaling, synchronous against asynchronous grids, cores.

``python -m semigrid.workloads.experiments`` runs them all at a small scale and prints a
line for each measurement.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semigrid.functions.blocks import FIELDS, read_block
from semigrid.functions.kernels import multiply_blocks
from semigrid.functions.model import calibrate
from semigrid.matrix import SparseMatrix
from semigrid.operators import structure as S
from semigrid.operators.measures import flops, kernel_op_counts
from semigrid.plans import multiply as P
from semigrid.plans.scratch import materialize
from semigrid.semiring import semiring
from semigrid.sources import generators as G


def seconds(make: Callable[[], DataFrame]) -> float:
    """Wall time of making a plan, with all that is written on the way, and running it without keeping its rows."""
    t = time.perf_counter()
    make().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def cached(m: SparseMatrix) -> SparseMatrix:
    return m.with_df(materialize(m.df, "operand"))


def kernel_scaling(a: SparseMatrix, b: SparseMatrix, qs: tuple[int, ...] = (1, 2, 4), kernels: tuple[str, ...] = ("heap_outer", "accumulator_row", "esc")) -> list[dict]:
    """Kernel time summed over all block products of a q by q grid, with the operation counts beside it.

    Blocks are packed, and the right operand is turned, once before; the time is that of the
    kernels alone.
    """
    out = []
    for q in qs:
        left, right = P.store_blocks(a, q, q, "columns"), P.store_blocks(b, q, q, "rows")
        met = left.df.select(F.col("bj").alias("bk"), *FIELDS).join(right.df.select(F.col("bi").alias("bk"), *[F.col(f).alias(f"r_{f}") for f in FIELDS]), "bk").drop("bk")
        ops = kernel_op_counts(a, b, q).first().asDict()
        for kernel in kernels:
            total = met.mapInArrow(_timed(kernel, (left.height, left.width, right.width)), "s double").agg(F.sum("s")).first()[0]
            out.append({"q": q, "kernel": kernel, "seconds": total or 0.0, **ops})
    return out


def _timed(kernel: str, sizes: tuple[int, int, int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spent = []
            for row in range(batch.num_rows):
                x, y = read_block(batch, row, 0), read_block(batch, row, 4)
                t = time.perf_counter()
                multiply_blocks(kernel, x, y, semiring("plus_times"), sizes)
                spent.append(time.perf_counter() - t)
            yield pa.RecordBatch.from_arrays([pa.array(spent, pa.float64())], ["s"])

    return run


def gamma(rows: list[dict], kernel: str) -> float:
    """Seconds an operation of a kernel, by regression over runs."""
    key = "classical_ops" if kernel == "accumulator_row" else "heap_ops"
    mine = [r for r in rows if r["kernel"] == kernel]
    return calibrate([r[key] for r in mine], [r["seconds"] for r in mine])


def strong_scaling(a: SparseMatrix, b: SparseMatrix, grids: tuple[int, ...] = (1, 2, 4), method: str = "fused_grid") -> list[dict]:
    """Time and speed-up over grids of more and more cells; speed-up is against the smallest grid."""
    seconds(lambda: P.METHODS[method](a, b, grid=(grids[0],) * 2).df)  # the first run compiles
    rows = [{"cells": q * q, "seconds": seconds(lambda q=q: P.METHODS[method](a, b, grid=(q, q)).df)} for q in grids]
    return [r | {"speedup": rows[0]["seconds"] / r["seconds"], "efficiency": rows[0]["seconds"] / r["seconds"] / (r["cells"] / rows[0]["cells"])} for r in rows]


def weak_scaling(spark: SparkSession, scales: tuple[int, ...] = (8, 10), per_column: int = 10) -> list[dict]:
    """Tall-skinny products whose size grows with the cells, normalised to the first."""
    rows = []
    for k, scale in enumerate(scales):
        a, b = cached(G.rmat(spark, scale)), cached(G.tall_skinny(spark, 1 << scale, 8 << k, per_column))
        rows.append({"n": 1 << scale, "k": 8 << k, "per_column": per_column, "cells": 4**k, "seconds": seconds(lambda: P.fused_grid(a, b, grid=(2**k, 2**k)).df)})  # noqa: B023
    return [r | {"normalised": r["seconds"] / rows[0]["seconds"]} for r in rows]


def compare_sync_async(a: SparseMatrix, b: SparseMatrix, grid: int = 2, repeats: int = 2) -> dict:
    """Panel grid with a barrier after each stage against the fused grid: best of some runs."""
    sync = min(seconds(lambda: P.panel_grid(a, b, grid=(grid, grid), barrier=True).df) for _ in range(repeats))
    free = min(seconds(lambda: P.fused_grid(a, b, grid=(grid, grid)).df) for _ in range(repeats))
    return {"sync": sync, "async": free, "ratio": sync / free, "flops": flops(a, b).first()[0]}


def cell_seconds(a: SparseMatrix, b: SparseMatrix, grid: int = 4, kernel: str = "esc") -> list[float]:
    """Kernel seconds of each cell of a fused grid; what ``wait_share`` is taken of."""
    left, right = P.store_blocks(a, grid, grid, "columns"), P.store_blocks(b, grid, grid, "rows")
    met = left.df.select("bi", F.col("bj").alias("bk"), *FIELDS).join(right.df.select("bj", F.col("bi").alias("bk"), *[F.col(f).alias(f"r_{f}") for f in FIELDS]), "bk")
    timed = _timed(kernel, (left.height, left.width, right.width))

    def run(key: tuple, t: pa.Table) -> pa.Table:
        spent = [b.column(0).to_pylist() for b in timed(iter(t.select([*FIELDS, *[f"r_{f}" for f in FIELDS]]).combine_chunks().to_batches()))]
        return pa.table({"s": [sum(sum(x) for x in spent)]})

    return [r["s"] for r in met.groupBy("bi", "bj").applyInArrow(run, "s double").collect()]  # as many rows as cells


def wait_share(durations: list[float]) -> float:
    """Part of the time that workers wait for the slowest."""
    return 1 - sum(durations) / (len(durations) * max(durations)) if durations else 0.0


def session(cores: int) -> SparkSession:
    return SparkSession.builder.master(f"local[{cores}]").config("spark.driver.memory", "6g").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()


def cores_experiment(cores: tuple[int, ...] = (1, 2, 4, 8), scale: int = 11) -> list[dict]:
    """Synchronous against asynchronous time for each number of cores of a node, each in a process of its own."""
    code = f"import json, sys; from semigrid.workloads import experiments as E; s = E.session(int(sys.argv[1])); a = E.cached(E.G.rmat(s, {scale})); print('ROW', json.dumps(E.compare_sync_async(a, a, 4)))"
    rows = []
    for k in cores:
        said = subprocess.run([sys.executable, "-c", code, str(k)], capture_output=True, text=True, check=True, timeout=600, env=os.environ | {"PYTHONPATH": os.pathsep.join(sys.path)}).stdout
        rows.append({"cores": k} | json.loads(said.rpartition("ROW")[2]))
    return rows


def kernel_inputs(spark: SparkSession, scale: int = 10, side: int = 10) -> dict[str, tuple[SparseMatrix, SparseMatrix]]:
    """The four pairs of the kernel experiment, written once; the mesh is relabelled at random."""
    r, e, g = cached(G.rmat(spark, scale)), cached(G.erdos_renyi(spark, 1 << scale, 8)), G.grid3d(spark, side)
    p = G.random_permutation(spark, g.nrows)
    mixed = cached(S.permute_rows_by(S.permute_by(g, p), p))
    return {"scale_free": (r, r), "scale_free_by_permutation": (r, cached(G.random_permutation(spark, r.nrows))), "uniform": (e, e), "mesh_relabelled": (mixed, mixed)}


def main() -> None:
    spark = session(8)
    spark.sparkContext.setLogLevel("ERROR")
    say = lambda name, **x: print(json.dumps({"experiment": name} | {k: round(v, 4) if isinstance(v, float) else v for k, v in x.items()}), flush=True)
    for name, (a, b) in kernel_inputs(spark).items():
        runs = kernel_scaling(a, b, (1, 2, 4, 8), ("heap_outer", "accumulator_row"))
        for r in runs:
            say("kernels", input=name, **r)
        say("calibration", input=name, heap=gamma(runs, "heap_outer") * 1e9, classical=gamma(runs, "accumulator_row") * 1e9, unit="ns an operation")
    a = cached(G.rmat(spark, 14))
    for method in ("fused_grid", "panel_grid"):
        for r in strong_scaling(a, a, (1, 2, 4), method):
            say("strong_scaling", method=method, **r)
    for per_column in (1, 10, 100):
        for r in weak_scaling(spark, (9, 11, 13), per_column):
            say("weak_scaling", **r)
    say("waiting", share=wait_share(cell_seconds(a, a, 4)), cells=16)
    spark.stop()
    for r in cores_experiment():
        say("cores", **r)


if __name__ == "__main__":
    main()
