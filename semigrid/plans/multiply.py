"""Parallel products C = A·B over a semiring: relational, block-row, rotating grid, panel grid and fused grid.

Grid methods ship doubly compressed blocks. Each block is packed once, the left operand in
column form and the right one in row form; copies of one binary value travel, not entries with
keys. Blocks that several jobs read are stored, others go from packing to their cells. A task lays its blocks down as they come, takes its cells' pairs in order of
the inner block and holds one pair at a time beside the sums of its cell.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DataType

from semigrid.functions.blocks import FIELDS, block_arrays, block_columns, block_of_value, block_schema, block_value, columns_of, rows_of, value_arrays
from semigrid.functions.held import HeldBlocks, HeldSums
from semigrid.functions.kernels import KERNELS, choose_by_counts, choose_for_slices, multiply_blocks, sliced
from semigrid.functions.worker import small_batches
from semigrid.matrix import SparseMatrix, cut
from semigrid.plans.grid_lines import Axis, finer_axes
from semigrid.plans.scratch import guarded_broadcast, materialize
from semigrid.semiring import Semiring, semiring

#: Entries of an operand that may be sent to every executor.
BROADCAST_ENTRIES = 2_000_000
#: Products of one inner id that a task makes; ids with more are split. Entries of a list in one row.
SPLIT_PRODUCTS, LIST_ENTRIES = 4_000_000, 4096
#: Entries of a block in one row of a table; larger blocks are a number of rows.
BLOCK_ENTRIES = 250_000
#: Entries that a task holds while it packs blocks that are not stored. Bytes of a row group of stored blocks.
PACKED_ENTRIES, BLOCK_GROUP = 1_500_000, 8 << 20


def _check(a: SparseMatrix, b: SparseMatrix) -> None:
    if a.ncols != b.nrows:
        raise ValueError(f"inner dimensions differ: {a.ncols} and {b.nrows}")


def _product(a: DataFrame, b: DataFrame, ring: Semiring) -> DataFrame:
    """Unsummed products (i, j, v); the sides meet on the inner id."""
    left, right = a.select("i", F.col("j").alias("k"), F.col("v").alias("x")), b.select(F.col("i").alias("k"), "j", F.col("v").alias("y"))
    return left.join(right, "k").select("i", "j", ring.mul(F.col("x"), F.col("y")).alias("v"))


def _sum(df: DataFrame, ring: Semiring, *more: str) -> DataFrame:
    return df.groupBy("i", "j", *more).agg(ring.add(F.col("v")).alias("v"))


def result_type(a: SparseMatrix, b: SparseMatrix, ring: str | Semiring) -> DataType:
    """Type of the values of a product, as the optimizer derives it; nothing is run."""
    r = semiring(ring)
    return _sum(_product(a.df, b.df, r), r).schema["v"].dataType


def _split_sides(a: SparseMatrix, b: SparseMatrix, most: int) -> tuple[DataFrame, DataFrame]:
    """The sides with a column s that parts the rows of A of an inner id with over ``most`` products; B's rows are repeated for each part."""
    da = a.df.groupBy(F.col("j").alias("k")).agg(F.count(F.lit(1)).alias("da"))
    db = b.df.groupBy(F.col("i").alias("k")).agg(F.count(F.lit(1)).alias("db"))
    heavy = da.join(db, "k").filter(F.col("da") * F.col("db") > most).select("k", F.least(F.ceil(F.col("da") * F.col("db") / most), F.col("da")).cast("long").alias("fan"))
    heavy = guarded_broadcast(materialize(heavy, "heavy"), 32)
    fan = F.coalesce("fan", F.lit(1).cast("long"))
    left = a.df.select("i", F.col("j").alias("k"), F.col("v").alias("x")).join(heavy, "k", "left").withColumn("s", F.pmod(F.xxhash64("i"), fan))
    right = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("y")).join(heavy, "k", "left").withColumn("s", F.explode(F.sequence(F.lit(0).cast("long"), fan - 1)))
    return left.drop("fan"), right.drop("fan")


def relational(a: SparseMatrix, b: SparseMatrix, ring: str | Semiring = "plus_times", mask: DataFrame | None = None, salt: int | str = 1, most: int = SPLIT_PRODUCTS, where: Column | None = None) -> SparseMatrix:
    """Outer formulation in the optimizer's hands: join on the inner id, aggregate on the place.

    Sums are combined before their shuffle. ``mask`` (i, j), and ``where``, a condition on i
    and j, keep wanted places only, before the aggregation. ``salt`` splits each inner id of A over so many partitions,
    with B's rows repeated as often; "auto" does so for the ids alone whose counts give over
    ``most`` products, each into as many parts as it needs.
    """
    _check(a, b)
    r = semiring(ring)
    if salt == "auto":
        left, right = _split_sides(a, b, most)
    elif salt > 1:
        left = a.df.select("i", F.col("j").alias("k"), F.col("v").alias("x"), F.pmod(F.xxhash64("i"), F.lit(salt)).cast("int").alias("s"))
        right = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("y"), F.explode(F.sequence(F.lit(0), F.lit(salt - 1))).alias("s"))
    found = _product(a.df, b.df, r) if salt == 1 else left.join(right, ["k", "s"]).select("i", "j", r.mul(F.col("x"), F.col("y")).alias("v"))
    if where is not None:
        found = found.filter(where)
    if mask is not None:
        found = found.join(mask.select("i", "j").distinct(), ["i", "j"], "left_semi")
    return SparseMatrix(_sum(found, r), a.nrows, b.ncols)


def block_row_replicated(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times", limit: int = BROADCAST_ENTRIES, turns: bool = False) -> SparseMatrix:
    """One-dimensional: all of B at every worker, A where it is.

    When B has over ``limit`` entries, it is refused, or with ``turns`` goes to every worker in
    slabs that fit, one after the other.
    """
    _check(a, b)
    n = b.df.count()
    if n > limit:
        if not turns:
            raise ValueError("the right operand is too large to be replicated; use another method")
        return block_row(a, b, ring, -(-n // limit), limit, turns)
    r = semiring(ring)
    return SparseMatrix(_sum(_product(a.df, F.broadcast(b.df), r), r), a.nrows, b.ncols)


def block_row(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times", slabs: int = 4, limit: int = BROADCAST_ENTRIES, more: bool = False) -> SparseMatrix:
    """One-dimensional, staged: slabs of B's rows are sent out one after the other.

    Each stage is a job of its own, so one slab is at the workers at a time; its sums are
    written, and those of all stages are added at the end. ``more`` takes more slabs than asked
    for where one would have over ``limit`` entries.
    """
    _check(a, b)
    r = semiring(ring)
    while True:
        sizes = b.df.groupBy(cut("i", b.nrows, slabs).alias("s")).count().agg(F.max("count")).first()[0] or 0
        if sizes <= limit:
            break
        if not more or slabs >= b.nrows:
            raise ValueError("a slab is too large to be replicated; use more slabs")
        slabs = min(b.nrows, max(slabs + 1, -(-slabs * sizes // limit)))
    right = materialize(b.df.withColumn("s", cut("i", b.nrows, slabs)).repartition("s"), "slabs", "s")
    left = materialize(a.df.withColumn("s", cut("j", a.ncols, slabs)), "slabs", "s")
    total: DataFrame | None = None
    for s in range(slabs):
        stage = _product(left.filter(F.col("s") == s), F.broadcast(right.filter(F.col("s") == s)), r)
        stage = materialize(_sum(stage, r), "sums")
        total = stage if total is None else total.unionByName(stage)
    return SparseMatrix(_sum(total, r), a.nrows, b.ncols)


def with_blocks(m: SparseMatrix, rows: int, cols: int) -> DataFrame:
    """Entries with their block (bi, bj) on a grid; sizes need not divide."""
    return m.df.withColumns({"bi": cut("i", m.nrows, rows).cast("int"), "bj": cut("j", m.ncols, cols).cast("int")})


@dataclass(frozen=True)
class StoredBlocks:
    """Nonempty blocks of a grid, rows of arrays: (bi, bj, ids, start, minor, num), and with prefix t_ the other form if both are kept.

    Lean blocks have one binary value, block, in place of the four arrays. A block of more than
    ``BLOCK_ENTRIES`` entries is a number of rows, unless it was stored whole. ``places`` are the
    nonempty (bi, bj) where the blocks are not stored but part of a plan.
    """

    df: DataFrame
    nrows: int
    ncols: int
    down: Axis
    along: Axis
    kind: DataType
    places: tuple[tuple[int, int], ...] | None = None

    @property
    def rows(self) -> int:
        return self.down.blocks

    @property
    def cols(self) -> int:
        return self.along.blocks

    @property
    def height(self) -> int:
        return self.down.longest

    @property
    def width(self) -> int:
        return self.along.longest


def _block_axes(m: SparseMatrix, rows: int | Axis, cols: int | Axis) -> tuple[Axis, Axis]:
    down, along = (x if isinstance(x, Axis) else Axis(n, x) for x, n in ((rows, m.nrows), (cols, m.ncols)))
    return down, along


def _keyed(m: SparseMatrix, down: Axis, along: Axis, kind: DataType) -> DataFrame:
    return m.df.select(down.block("i").cast("int").alias("bi"), along.block("j").cast("int").alias("bj"), F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), F.col("v").cast(kind).alias("v"))


def store_blocks(m: SparseMatrix, rows: int | Axis, cols: int | Axis, form: str = "columns", kind: DataType | None = None, most: int | None = BLOCK_ENTRIES, lean: bool = False) -> StoredBlocks:
    """Packs each block once and writes it; ``form`` is columns, rows, or both.

    ``kind`` is the type that values take before they are packed, their own by default. Entries
    come sorted by block and inner id, so a task holds ``most`` of them; with none, whole blocks.
    ``lean`` blocks are one binary value for each form.
    """
    kind = kind or m.df.schema["v"].dataType
    _, value = value_arrays(kind)
    down, along = _block_axes(m, rows, cols)
    prefixes = [""] + (["t_"] if form == "both" else [])
    names = ["bi", "bj"] + [n for p in prefixes for n in ([f"{p}block"] if lean else [x for x, _ in block_columns(value, p)])]
    tops, lefts = down.corners(), along.corners()
    written = (lambda b: [pa.array([block_value(b)], pa.binary())]) if lean else (lambda b: block_arrays(b, value))

    def packed(key: tuple[int, int], parts: list[tuple]) -> pa.RecordBatch:
        i, j, v = (np.concatenate(x) for x in zip(*parts))
        entries = (i - tops[key[0]], j - lefts[key[1]], v)
        block = rows_of(entries) if form == "rows" else columns_of(entries)
        arrays = written(block) + (written(block.turned()) if form == "both" else [])
        return pa.RecordBatch.from_arrays([pa.array([k], pa.int32()) for k in key] + arrays, names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, parts, n = None, [], 0
        for batch in batches:
            bi, bj, *entries = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(5))
            ends = np.flatnonzero((bi[1:] != bi[:-1]) | (bj[1:] != bj[:-1])) + 1
            for s, e in zip([0, *ends.tolist()], [*ends.tolist(), len(bi)]):
                if s == e:
                    continue
                key = (int(bi[s]), int(bj[s]))
                if parts and (key != at or most and n >= most):
                    yield packed(at, parts)
                    parts, n = [], 0
                at = key
                parts.append(tuple(x[s:e].copy() for x in entries))
                n += e - s
        if parts:
            yield packed(at, parts)

    small_batches(m.df.sparkSession)
    schema = "bi int, bj int, " + ", ".join(f"{p}block binary" if lean else block_schema(kind, p) for p in prefixes)
    dealt = _keyed(m, down, along, kind).repartition("bi", "bj").sortWithinPartitions("bi", "bj", "i" if form == "rows" else "j")
    return StoredBlocks(materialize(dealt.mapInArrow(run, schema), "blocks", group=BLOCK_GROUP), m.nrows, m.ncols, down, along, kind)


def plan_blocks(m: SparseMatrix, rows: int | Axis, cols: int | Axis, form: str = "columns", most: int = PACKED_ENTRIES) -> StoredBlocks:
    """Lean blocks as part of a plan, for products that read them once; no table is written and Spark sorts nothing.

    A task holds the entries of its blocks, by block. When it has over ``most``, the largest
    block it holds goes out, so a block may be a number of rows, of ``BLOCK_ENTRIES`` entries at most.
    """
    kind = m.df.schema["v"].dataType
    down, along = _block_axes(m, rows, cols)
    tops, lefts = down.corners(), along.corners()
    names = ["bi", "bj", "block"] + (["t_block"] if form == "both" else [])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], list] = {}
        sizes: dict[tuple[int, int], int] = {}

        def packed(key: tuple[int, int]) -> Iterator[pa.RecordBatch]:
            i, j, v = (np.concatenate(x) for x in zip(*held.pop(key)))
            sizes.pop(key)
            for s in range(0, len(i), BLOCK_ENTRIES):
                at = slice(s, s + BLOCK_ENTRIES)
                entries = (i[at] - tops[key[0]], j[at] - lefts[key[1]], v[at])
                block = rows_of(entries) if form == "rows" else columns_of(entries)
                values = [block_value(block)] + ([block_value(block.turned())] if form == "both" else [])
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()) for k in key] + [pa.array([x], pa.binary()) for x in values], names)

        for batch in batches:
            bi, bj, *entries = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(5))
            order = np.lexsort((bj, bi))
            bi, bj, entries = bi[order], bj[order], [x[order] for x in entries]
            ends = np.flatnonzero((bi[1:] != bi[:-1]) | (bj[1:] != bj[:-1])) + 1
            for s, e in zip([0, *ends.tolist()], [*ends.tolist(), len(bi)]):
                if s < e:
                    key = (int(bi[s]), int(bj[s]))
                    held.setdefault(key, []).append(tuple(x[s:e].copy() for x in entries))
                    sizes[key] = sizes.get(key, 0) + e - s
            while sum(sizes.values()) > most:
                yield from packed(max(sizes, key=sizes.get))
        for key in list(held):
            yield from packed(key)

    small_batches(m.df.sparkSession)
    keyed = _keyed(m, down, along, kind)
    places = tuple((r.bi, r.bj) for r in keyed.select("bi", "bj").distinct().collect())
    dealt = keyed.repartition("bi", "bj").mapInArrow(run, ", ".join(["bi int, bj int", *(f"{n} binary" for n in names[2:])]))
    return StoredBlocks(dealt, m.nrows, m.ncols, down, along, kind, places)


def unpack_blocks(b: StoredBlocks, form: str = "columns", prefix: str = "") -> SparseMatrix:
    """The entries of stored blocks, by array functions alone."""
    f = {n: F.col(prefix + n) for n in FIELDS}
    at = b.df.select("bi", "bj", F.posexplode(f["ids"]).alias("k", "major"), f["start"].alias("start"), f["minor"].alias("minor"), f["num"].alias("num"))
    low, n = F.get("start", F.col("k")), F.get("start", F.col("k") + 1) - F.get("start", F.col("k"))
    piece = lambda c: F.slice(c, (low + 1).cast("int"), n.cast("int"))
    each = at.select("bi", "bj", "major", F.explode(F.arrays_zip(piece("minor").alias("minor"), piece("num").alias("num"))).alias("e"))
    i, j = (F.col("e.minor"), F.col("major")) if form == "columns" else (F.col("major"), F.col("e.minor"))
    return SparseMatrix(each.select((i + b.down.corner("bi")).alias("i"), (j + b.along.corner("bj")).alias("j"), F.col("e.num").alias("v")), b.nrows, b.ncols)


def partnered(a: SparseMatrix, b: SparseMatrix) -> tuple[SparseMatrix, SparseMatrix]:
    """The operands without entries whose inner id the other lacks."""
    left = a.df.join(b.df.select(F.col("i").alias("j")).distinct(), "j", "left_semi").select("i", "j", "v")
    right = b.df.join(a.df.select(F.col("j").alias("i")).distinct(), "i", "left_semi").select("i", "j", "v")
    return a.with_df(left), b.with_df(right)


def _places(b: StoredBlocks) -> list[tuple[int, int]]:
    """The nonempty blocks."""
    return list(b.places) if b.places is not None else [tuple(r) for r in b.df.select("bi", "bj").distinct().collect()]


def _multiplied(dealt: DataFrame, a: StoredBlocks, b: StoredBlocks, ring: str | Semiring, kernel: str, kind: DataType, stats: bool = False) -> DataFrame:
    """(i, j, v) of cells from rows (ci, cj, bk, side, own, block), one task a cell or more.

    A task lays the blocks down as they come, up to a limit in memory, and takes them in order of cell,
    inner block and side. The blocks of A for one inner block, and one block of B at a time, are all that
    is held beside the results of the cell. With ``stats``: (ci, cj, bk, flops, ni, nzc, nzr) of each pair instead.
    """
    ring = semiring(ring)
    sizes, tops, lefts = (a.height, a.width, b.width), a.down.corners(), b.along.corners()
    dtype, value = value_arrays(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, at, left, sums, blocks = None, None, [], HeldSums(ring), HeldBlocks()

        def results() -> Iterator[pa.RecordBatch]:
            for i, j, v in sums.results():
                yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(v.astype(dtype), value)], ["i", "j", "v"])

        for batch in batches:
            for row, key in enumerate(zip(*(batch.column(k).to_pylist() for k in range(5)))):
                blocks.add(key, block_of_value(batch.column(5)[row].as_buffer()))
        for (ci, cj, bk, side, own), block in blocks.ordered():
            if (ci, cj) != cell:
                yield from results()
                cell, at = (ci, cj), None
            if bk != at:
                at, left = bk, []
            if side == 0:
                left.append((own, block))
                continue
            for bi, x in left:
                if stats:
                    _, s = multiply_blocks(kernel, x, block, ring, sizes)
                    yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()) for n in (ci, cj, bk, *(s[k] for k in ("flops", "ni", "nzc", "nzr")))], ["ci", "cj", "bk", "flops", "ni", "nzc", "nzr"])
                    continue
                named = choose_for_slices(x, block, sizes) if kernel == "auto" else kernel
                for p, q in sliced(x, block, named == "dense"):
                    i, j, v = KERNELS[named](p, q, ring, sizes)[0]
                    sums.add((i + tops[bi], j + lefts[own], v))
        yield from results()

    return dealt.repartition("ci", "cj").mapInArrow(run, "ci long, cj long, bk long, flops long, ni long, nzc long, nzr long" if stats else f"i long, j long, v {kind.simpleString()}")


def _added(df: DataFrame, ring: Semiring, kind: DataType) -> DataFrame:
    """The sums of (i, j, v) by place, in tasks that hold a bounded part and merge the rest from their own disk; Spark holds no table of places."""
    dtype, value = value_arrays(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = HeldSums(ring)
        for batch in batches:
            sums.add(tuple(batch.column(k).to_numpy(zero_copy_only=False) for k in range(3)))
        for i, j, v in sums.results():
            yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(v.astype(dtype), value)], ["i", "j", "v"])

    return df.select("i", "j", "v").repartition("i", "j").mapInArrow(run, f"i long, j long, v {kind.simpleString()}")


def _dealt(a: StoredBlocks, b: StoredBlocks, inner: tuple[int, int] = (1, 1), prefix: str = "") -> DataFrame:
    """Every block of A for the cells of its grid row, of B for those of its grid column; ``inner`` blocks a side make one cell.

    On a grid that was refined, blocks go only to cells where they meet a nonempty one.
    """
    coarse = lambda c, n: F.floor(F.col(c) / n).cast("int")
    if max(a.down.fine, a.along.fine, b.along.fine) == 1:
        every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
        x, y = a.df.withColumn("cj", every(-(-b.cols // inner[1]))), b.df.withColumn("ci", every(-(-a.rows // inner[0])))
    else:
        spark = a.df.sparkSession
        rows = sorted({(k, i // inner[0]) for i, k in _places(a)})
        cols = sorted({(k, j // inner[1]) for k, j in _places(b)})
        x = a.df.join(F.broadcast(spark.createDataFrame(cols, "bj int, cj int")), "bj")
        y = b.df.join(F.broadcast(spark.createDataFrame(rows, "bi int, ci int")), "bi")
    left = x.select(coarse("bi", inner[0]).alias("ci"), "cj", F.col("bj").alias("bk"), F.lit(0).alias("side"), F.col("bi").alias("own"), "block")
    right = y.select("ci", coarse("bj", inner[1]).alias("cj"), F.col("bi").alias("bk"), F.lit(1).alias("side"), F.col("bj").alias("own"), F.col(prefix + "block").alias("block"))
    return left.unionByName(right)


def _stored_pair(a: SparseMatrix, b: SparseMatrix, r: int, s: int, c: int, ring, refine: bool = True, once: bool = False) -> tuple[StoredBlocks, StoredBlocks, DataType]:
    """Both operands on a grid as fine as asked for, or finer where counts say that its blocks or cells are too large for a task.

    Blocks are stored, but for products on a refined grid that read them ``once``.
    """
    _check(a, b)
    kind = result_type(a, b, ring)
    value_arrays(kind)
    (down, mid, along), whole = finer_axes(a, b, r, s, c) if refine else ((Axis(a.nrows, r), Axis(a.ncols, s), Axis(b.ncols, c)), False)
    a, b = (a, b) if whole else partnered(a, b)
    if once and max(down.fine, mid.fine, along.fine) > 1:
        return plan_blocks(a, down, mid, "columns"), plan_blocks(b, mid, along, "rows"), kind
    return store_blocks(a, down, mid, "columns", lean=True), store_blocks(b, mid, along, "rows", lean=True), kind


def panel_grid(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times", grid: tuple[int, int] = (2, 2), panels: int | None = None, kernel: str = "esc", barrier: bool = False, eager: bool = False) -> SparseMatrix:
    """Two-dimensional, synchronous: in stage s, panel s of A goes along the grid rows and panel s of B along the columns.

    ``barrier`` ends each stage with a written table, ``eager`` adds it to the result
    at once; otherwise the stages form one plan and sums are merged at its end. Blocks are
    packed and written once, before the first stage, whose sums are a result as they are.
    """
    panels = panels or max(grid)
    r = semiring(ring)
    left, right, kind = _stored_pair(a, b, grid[0], panels, grid[1], ring)
    dealt = _dealt(left, right)
    total: DataFrame | None = None
    for s in range(panels):
        stage = _multiplied(dealt.filter(F.call_function("div", F.col("bk"), F.lit(left.along.fine)) == s), left, right, r, kernel, kind)
        stage = materialize(stage, "stage") if barrier else stage
        if total is None:
            total = stage
        else:
            total = _added(total.unionByName(stage), r, kind) if eager else total.unionByName(stage)
    return SparseMatrix(total if eager else _sum(total, r), a.nrows, b.ncols)


def fused_grid(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times", grid: tuple[int, int] = (2, 2), split: int = 1, kernel: str = "esc") -> SparseMatrix:
    """Two-dimensional, without barriers: every cell has its pairs in one shuffle and works at its own pace.

    ``split`` cuts each block along the inner dimension: a task holds one piece of each
    operand while the next ones are fetched. A cell sums its own results, so there is
    no shuffle after the one that ships the blocks.
    """
    left, right, kind = _stored_pair(a, b, grid[0], max(grid) * split, grid[1], ring, once=True)
    return SparseMatrix(_multiplied(_dealt(left, right), left, right, ring, kernel, kind), a.nrows, b.ncols)


def two_level_grid(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times", grid: tuple[int, int] = (2, 2), inner: int = 2, kernel: str = "esc") -> SparseMatrix:
    """Coarse cells are tasks, each with ``inner`` by ``inner`` fine cells: blocks are shipped once for a coarse cell."""
    left, right, kind = _stored_pair(a, b, grid[0] * inner, max(grid), grid[1] * inner, ring, once=True)
    return SparseMatrix(_multiplied(_dealt(left, right, (inner, inner)), left, right, ring, kernel, kind), a.nrows, b.ncols)


def dual_blocks(m: SparseMatrix, q: int) -> StoredBlocks:
    """A square matrix with both forms of each block, written once: twice the storage, and no transposition for either side of a product. Spark sorts nothing."""
    both, _ = finer_axes(m, m, q, q, q, square=True)
    blocks = plan_blocks(m, both[0], both[0], "both")
    return replace(blocks, df=materialize(blocks.df, "blocks", group=BLOCK_GROUP))


def square_dual(blocks: StoredBlocks, ring: str = "plus_times", kernel: str = "heap_outer") -> SparseMatrix:
    """A·A from one stored table: its column form stands on the left, its row form on the right."""
    none = blocks.df.sparkSession.range(0).select(F.col("id").alias("i"), F.col("id").alias("j"), F.col("id").cast(blocks.kind).alias("v"))
    m = SparseMatrix(none, blocks.nrows, blocks.ncols)
    kind = result_type(m, m, ring)
    return SparseMatrix(_multiplied(_dealt(blocks, blocks, prefix="t_"), blocks, blocks, ring, kernel, kind), blocks.nrows, blocks.ncols)


def pair_stats(a: SparseMatrix, b: SparseMatrix, q: int, kernel: str = "heap_outer") -> DataFrame:
    """(ci, cj, bk, flops, ni, nzc, nzr): what the kernel itself counted for each pair of blocks of a q by q grid."""
    _check(a, b)
    left, right = store_blocks(a, q, q, "columns", most=None, lean=True), store_blocks(b, q, q, "rows", most=None, lean=True)
    return _multiplied(_dealt(left, right), left, right, "plus_times", kernel, result_type(a, b, "plus_times"), stats=True)


def kernel_choices(a: SparseMatrix, b: SparseMatrix, q: int) -> DataFrame:
    """(kernel, pairs): what the chooser takes for the pairs of blocks with common ids, on a q by q grid.

    It decides by counts, so the blocks themselves are not made.
    """
    _check(a, b)
    size = max(-(-a.nrows // q), -(-a.ncols // q), -(-b.ncols // q))
    da = a.df.groupBy(cut("i", a.nrows, q).alias("bi"), F.col("j").alias("k")).agg(F.count(F.lit(1)).alias("da"))
    db = b.df.groupBy(cut("j", b.ncols, q).alias("bj"), F.col("i").alias("k")).agg(F.count(F.lit(1)).alias("db"))
    inner = cut("k", a.ncols, q).alias("bk")
    x = da.groupBy("bi", inner).agg(F.sum("da").alias("na"), F.count(F.lit(1)).alias("nzc"))
    y = db.groupBy("bj", inner).agg(F.sum("db").alias("nb"), F.count(F.lit(1)).alias("nzr"))
    met = da.join(db, "k").groupBy("bi", "bj", inner).agg(F.sum(F.col("da") * F.col("db")).alias("flops"), F.count(F.lit(1)).alias("ni"))
    each = met.join(x, ["bi", "bk"]).join(y, ["bj", "bk"]).select((F.col("na") + F.col("nb")).alias("nnz"), "flops", "nzc", "nzr", "ni")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts = zip(*(batch.column(k).to_pylist() for k in range(5)))
            yield pa.RecordBatch.from_arrays([pa.array([choose_by_counts(size, *c) for c in counts], pa.string())], ["kernel"])

    return each.mapInArrow(run, "kernel string").groupBy("kernel").agg(F.count(F.lit(1)).alias("pairs"))


def shift(blocks: DataFrame, axis: str, by: int, q: int) -> DataFrame:
    """Circular move of blocks: to the left along ``bj``, or up along ``bi``."""
    return blocks.withColumn(axis, F.pmod(F.col(axis) - by, F.lit(q)).cast("int"))


def rotating_grid(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times", q: int = 2, kernel: str = "esc") -> SparseMatrix:
    """Two-dimensional on a square grid: skew A by its rows and B by its columns, then multiply and shift q times.

    Each round's operands are written to the shared folder, so the plan does not grow.
    """
    left, right, kind = _stored_pair(a, b, q, q, q, ring, refine=False)
    # bi and bj are places on the grid from here on; bk is the inner block that a block belongs to
    x = left.df.withColumn("bk", F.col("bj")).withColumn("bj", F.pmod(F.col("bj") - F.col("bi"), F.lit(q)).cast("int"))
    y = right.df.withColumn("bk", F.col("bi")).withColumn("bi", F.pmod(F.col("bi") - F.col("bj"), F.lit(q)).cast("int"))
    total: DataFrame | None = None
    for k in range(q):
        x, y = (materialize(shift(d, axis, 1, q) if k else d, "rotated") for d, axis in ((x, "bj"), (y, "bi")))
        here = lambda d, side, own: d.select(F.col("bi").alias("ci"), F.col("bj").alias("cj"), "bk", F.lit(side).alias("side"), F.col(own).alias("own"), "block")
        stage = _multiplied(here(x, 0, "bi").unionByName(here(y, 1, "bj")), left, right, ring, kernel, kind)
        total = stage if total is None else total.unionByName(stage)
    return SparseMatrix(_sum(total, semiring(ring)), a.nrows, b.ncols)


def row_by_row(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times") -> SparseMatrix:
    """Each row of A collects the rows of B that it names, all at once, then sums them.

    A long row of B is a number of lists, of about ``LIST_ENTRIES`` entries each.
    """
    _check(a, b)
    r = semiring(ring)
    rows = a.df.select("i", F.col("j").alias("k"), F.col("v").alias("x"))
    lists = F.ceil(F.count(F.lit(1)) / LIST_ENTRIES).cast("long")
    parted = b.df.join(b.df.groupBy("i").agg(lists.alias("fan")), "i").withColumn("s", F.pmod(F.xxhash64("j"), F.col("fan")))
    listed = parted.groupBy(F.col("i").alias("k"), "s").agg(F.collect_list(F.struct("j", F.col("v").alias("y"))).alias("row"))
    each = rows.join(listed, "k").select("i", "x", F.explode("row").alias("e")).select("i", F.col("e.j").alias("j"), r.mul(F.col("x"), F.col("e.y")).alias("v"))
    return SparseMatrix(_sum(each, r), a.nrows, b.ncols)


def column_by_column(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times") -> SparseMatrix:
    """The mirror of rows: the transposed product of the transposes, with a commutative product."""
    return row_by_row(b.T, a.T, ring).T


def single_block(a: SparseMatrix, b: SparseMatrix, kernel: str, ring: str = "plus_times", cells: int = 4) -> SparseMatrix:
    """A named kernel on row slabs of A with all of B: for comparing kernels."""
    left, right, kind = _stored_pair(a, b, cells, 1, 1, ring, once=True)
    return SparseMatrix(_multiplied(_dealt(left, right), left, right, ring, kernel, kind), a.nrows, b.ncols)


def delta_product(a: SparseMatrix, b: SparseMatrix, da: SparseMatrix, db: SparseMatrix, c: SparseMatrix, ring: str = "plus_times") -> SparseMatrix:
    """C for A + dA and B + dB from C for A and B: only products with a change are made."""
    r = semiring(ring)
    parts = c.df.unionByName(_product(da.df, b.df, r)).unionByName(_product(a.df, db.df, r)).unionByName(_product(da.df, db.df, r))
    return SparseMatrix(_sum(parts, r), a.nrows, b.ncols)


def rings_summary(a: SparseMatrix, b: SparseMatrix, rings: list[str], limit: int = BROADCAST_ENTRIES, buckets: int = 64) -> DataFrame:
    """(ring, n, least, greatest) of the entries of the product over each semiring, as doubles; no product is shuffled.

    A is dealt by its rows once, in a bucketed table. B goes to every worker in slabs of columns with at most
    ``limit`` entries if columns allow, one after the other. So all products of a place meet in one task, for all semirings at once.
    """
    _check(a, b)
    spark, slabs = a.df.sparkSession, 1
    while True:
        most = b.df.groupBy(cut("j", b.ncols, slabs).alias("s")).count().agg(F.max("count")).first()[0] or 0
        if most <= limit or slabs >= b.ncols:
            break
        slabs = min(b.ncols, max(slabs + 1, -(-slabs * most // limit)))
    right = materialize(b.df.withColumn("s", cut("j", b.ncols, slabs)).repartition("s"), "slabs", "s")
    name = f"semigrid_rows_{uuid.uuid4().hex}"
    sums = [semiring(r).add(semiring(r).mul(F.col("x"), F.col("y"))).cast("double").alias(r) for r in rings]
    ends = [f(r).alias(f"{r}_{e}") for r in rings for e, f in (("least", F.min), ("greatest", F.max))]
    parts: DataFrame | None = None
    a.df.repartition(buckets, "i").write.format("parquet").bucketBy(buckets, "i").saveAsTable(name)
    try:
        left = spark.table(name).select("i", F.col("j").alias("k"), F.col("v").alias("x"))
        for s in range(slabs):
            met = left.join(F.broadcast(right.filter(F.col("s") == s).select(F.col("i").alias("k"), "j", F.col("v").alias("y"))), "k")
            part = materialize(met.groupBy("i", "j").agg(*sums).agg(F.count(F.lit(1)).alias("n"), *ends), "rings")
            parts = part if parts is None else parts.unionByName(part)
    finally:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
    each = F.explode(F.array(*[F.struct(F.lit(r).alias("ring"), "n", F.col(f"{r}_least").alias("least"), F.col(f"{r}_greatest").alias("greatest")) for r in rings]))
    return parts.select(each.alias("e")).select("e.*").groupBy("ring").agg(F.sum("n").alias("n"), F.min("least").alias("least"), F.max("greatest").alias("greatest"))


METHODS = {"relational": relational, "block_row": block_row, "block_row_replicated": block_row_replicated, "rotating_grid": rotating_grid, "panel_grid": panel_grid, "fused_grid": fused_grid, "two_level_grid": two_level_grid}


def spgemm(a: SparseMatrix, b: SparseMatrix, ring: str = "plus_times", method: str = "auto", **options) -> SparseMatrix:
    """C = A·B; ``auto`` weighs what each method would ship, and takes the grid or the splitting that goes with it."""
    if method == "auto":
        from semigrid.plans.planner import plan_product

        plan = plan_product(a, b)
        method, options = plan["method"], plan["options"] | options
    return METHODS[method](a, b, ring, **options)
