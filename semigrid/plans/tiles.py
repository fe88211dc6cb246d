"""Products of a matrix of positive whole numbers with its own transpose, tile by tile, without a shuffle of products.

Rows are dealt into slabs. Inner ids with many entries stand in dense arrays, the others are met
as lists. A task holds some slabs and reads all the others, one at a time.
"""

from __future__ import annotations

from collections.abc import Iterator
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semigrid.functions.worker import small_batches
from semigrid.matrix import SparseMatrix
from semigrid.plans.scratch import guarded_broadcast, materialize

#: Rows of a slab, slabs that a task holds, and products of lists made at once.
SLAB_ROWS, HELD_SLABS, LIST_PRODUCTS = 1500, 4, 2_000_000
#: An inner id is dense when more than one row in so many has it; so many dense ones at most.
DENSE_SHARE, DENSE_IDS = 16, 4096
_LISTS = "ids array<bigint>, norms array<double>, hrow array<int>, hcol array<int>, hval array<bigint>, lword array<bigint>, lrow array<int>, lval array<bigint>"
_NAMES = [x.split()[0] for x in _LISTS.split(", ")]


def fits(a: SparseMatrix, bounds) -> bool:
    """Whether all values are positive whole numbers, so that a product is zero only where rows share no id, and sums are exact as doubles."""
    return isinstance(a.df.schema["v"].dataType, (T.LongType, T.IntegerType)) and bounds["n"] > 0 and bounds["low"] > 0 and bounds["most"] < 1 << 53


def bounds_of(m: SparseMatrix):
    rows = m.df.groupBy("i").agg(F.min("v").alias("low"), F.max("v").alias("high"), F.sum(F.col("v").cast("double") * F.col("v")).alias("square"))
    return rows.agg(F.count(F.lit(1)).alias("n"), F.min("low").alias("low"), F.max("high").alias("high"), F.max("square").alias("most")).first()


def _slabs(m: SparseMatrix, rows: int) -> tuple[DataFrame, int, int]:
    """One row of lists for each slab, the number of slabs and that of dense ids. Inner ids of one row alone are in no product of two rows, but stay for those of a row with itself."""
    n = -(-rows // SLAB_ROWS)
    counts = m.df.groupBy("j").agg(F.count(F.lit(1)).alias("n"))
    heavy = [r["j"] for r in counts.filter(F.col("n") * DENSE_SHARE > rows).orderBy(F.desc("n"), "j").limit(DENSE_IDS).collect()]
    spark = m.df.sparkSession
    kind = m.df.schema["j"].dataType.simpleString()
    dense = spark.createDataFrame(list(zip(heavy, range(len(heavy)))), f"j {kind}, h int")
    words = materialize(counts.select("j", F.monotonically_increasing_id().alias("w")), "words")
    coded = m.df.join(F.broadcast(dense), "j", "left").join(guarded_broadcast(words, 64), "j").select(F.pmod(F.xxhash64("i"), F.lit(n)).cast("int").alias("slab"), "i", "h", "w", F.col("v").cast("long").alias("v"))

    def pack(key: tuple, t: pa.Table) -> pa.Table:
        i, v, w = (t.column(c).to_numpy() for c in ("i", "v", "w"))
        h = t.column("h").fill_null(-1).to_numpy()
        ids, row = np.unique(i, return_inverse=True)
        norms = np.sqrt(np.bincount(row, weights=v.astype(np.float64) ** 2))
        up, low = np.flatnonzero(h >= 0), np.flatnonzero(h < 0)
        low = low[np.argsort(w[low], kind="stable")]
        lists = [(ids, pa.int64()), (norms, pa.float64()), (row[up], pa.int32()), (h[up], pa.int32()), (v[up], pa.int64()), (w[low], pa.int64()), (row[low], pa.int32()), (v[low], pa.int64())]
        return pa.table([pa.array([key[0].as_py()], pa.int32()), *[pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), pa.array(x).cast(k)) for x, k in lists]], names=["slab", *_NAMES])

    return materialize(coded.groupBy("slab").applyInArrow(pack, f"slab int, {_LISTS}"), "slabs"), n, len(heavy)


class _Slab:
    def __init__(self, lists: list[np.ndarray], dense: int, kind: type):
        self.ids, self.norms, hrow, hcol, hval, self.word, self.row, self.val = lists
        self.dense = np.zeros((len(self.ids), dense), kind)
        self.dense[hrow, hcol] = hval
        head = np.flatnonzero(np.r_[True, self.word[1:] != self.word[:-1]]) if len(self.word) else np.zeros(0, np.int64)
        self.words, self.start = self.word[head], np.r_[head, len(self.word)]

    def times(self, other: _Slab) -> np.ndarray:
        """Products of all rows with all rows of the other slab."""
        out = (self.dense @ other.dense.T).astype(np.float64)
        flat, cols = out.reshape(-1), len(other.ids)
        _, x, y = np.intersect1d(self.words, other.words, assume_unique=True, return_indices=True)
        n, m = self.start[x + 1] - self.start[x], other.start[y + 1] - other.start[y]
        group = np.cumsum(n * m) // LIST_PRODUCTS
        for g in np.unique(group):
            at = group == g
            rows, times = n[at], np.repeat(m[at], n[at])
            left = np.repeat(self.start[x[at]] - (np.cumsum(rows) - rows), rows) + np.arange(rows.sum())
            low = np.repeat(other.start[y[at]], rows)
            right = np.repeat(low - (np.cumsum(times) - times), times) + np.arange(times.sum())
            left = np.repeat(left, times)
            np.add.at(flat, self.row[left].astype(np.int64) * cols + other.row[right], self.val[left] * other.val[right])
        return out


def _millionths(x: np.ndarray) -> np.ndarray:
    """Millionths, halves away from zero by the shortest decimal, as Spark rounds doubles."""
    scaled = x * 1e6
    out = np.floor(scaled + 0.5).astype(np.int64)
    for at in zip(*np.nonzero(np.abs(scaled - np.floor(scaled) - 0.5) < 1e-6)):
        out[at] = int((Decimal(repr(float(x[at]))) * 1_000_000).quantize(Decimal(1), ROUND_HALF_UP))
    return out


def _run(m: SparseMatrix, bounds, schema: str, start, each, end) -> DataFrame:
    """``start`` makes the state of a held slab, ``each`` takes a tile and may give batches, ``end`` gives what is left of the state."""
    small_batches(m.df.sparkSession)
    slabs, n, dense = _slabs(m, bounds["n"])
    kind = np.float32 if bounds["most"] < 1 << 24 else np.float64
    groups = -(-n // HELD_SLABS)
    group = F.call_function("div", F.col("slab"), F.lit(HELD_SLABS)).cast("int")
    left = slabs.select(group.alias("g"), F.lit(0).alias("side"), *_NAMES)
    right = slabs.select(F.explode(F.sequence(F.lit(0), F.lit(groups - 1))).alias("g"), F.lit(1).alias("side"), *_NAMES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held = None, []
        for batch in batches:
            for row, (g, side) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())):
                if g != at:
                    for h, state in held:
                        yield from end(h, state)
                    at, held = g, []
                slab = _Slab([batch.column(2 + k)[row].values.to_numpy(zero_copy_only=False) for k in range(len(_NAMES))], dense, kind)
                if side == 0:
                    held.append((slab, start(slab)))
                    continue
                for h, state in held:
                    yield from each(h, slab, h.times(slab), state)
        for h, state in held:
            yield from end(h, state)

    return left.unionByName(right).repartition(max(groups, 1), "g").sortWithinPartitions("g", "side").mapInArrow(run, schema)


def gram(m: SparseMatrix, bounds) -> DataFrame:
    """(i, j, v): all products that are not zero."""

    def each(x: _Slab, y: _Slab, tile: np.ndarray, state) -> Iterator[pa.RecordBatch]:
        step = max(1, 200_000 // len(y.ids))
        for s in range(0, len(x.ids), step):
            r, c = np.nonzero(tile[s : s + step])
            yield pa.RecordBatch.from_arrays([pa.array(x.ids[s + r]), pa.array(y.ids[c]), pa.array(tile[s + r, c].astype(np.int64))], ["i", "j", "v"])

    return _run(m, bounds, "i long, j long, v long", lambda x: None, each, lambda x, s: iter(()))


def gram_topk(m: SparseMatrix, bounds, k: int, cosine: bool) -> DataFrame:
    """(i, j, score, rank): the k greatest products of each row with later rows, or with ``cosine`` the k greatest millionths of cosines with other rows; ties go to smaller ids."""

    def start(x: _Slab) -> list:
        return [np.full((len(x.ids), k), -1, np.int64), np.full((len(x.ids), k), np.iinfo(np.int64).max)]

    def each(x: _Slab, y: _Slab, tile: np.ndarray, state: list) -> Iterator[pa.RecordBatch]:
        score = _millionths(tile / (x.norms[:, None] * y.norms[None, :])) if cosine else tile.astype(np.int64)
        wrong = x.ids[:, None] == y.ids[None, :] if cosine else x.ids[:, None] >= y.ids[None, :]
        score[wrong | (tile == 0)] = -1
        width = len(y.ids)
        best = min(k, width)
        top = np.argpartition(score * width - np.arange(width), width - best, axis=1)[:, width - best :]  # ids ascend in a slab
        found = np.take_along_axis(score, top, 1)
        scores, ids = np.hstack([state[0], found]), np.hstack([state[1], y.ids[top]])
        order = np.lexsort((ids, -scores), axis=1)[:, :k]
        state[0], state[1] = np.take_along_axis(scores, order, 1), np.take_along_axis(ids, order, 1)
        return iter(())

    def end(x: _Slab, state: list) -> Iterator[pa.RecordBatch]:
        r, c = np.nonzero(state[0] >= 0)
        yield pa.RecordBatch.from_arrays([pa.array(x.ids[r]), pa.array(state[1][r, c]), pa.array(state[0][r, c]), pa.array((c + 1).astype(np.int64))], ["i", "j", "score", "rank"])

    return _run(m, bounds, "i long, j long, score long, rank long", start, each, end)
