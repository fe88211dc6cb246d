"""Where the lines of a grid lie: contiguous ranges of ids, and how much finer counts ask them to be."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semigrid.matrix import SparseMatrix, cut

#: Operands with fewer entries together keep the grid that was asked for.
SMALL_OPERANDS = 1_500_000
#: Entries of both operands for one inner range, products of a cell, cells a side, and how often operands may be shipped for finer cells.
INNER_ENTRIES, CELL_PRODUCTS, MOST_CELLS, MOST_SHIPS = 250_000, 2_000_000, 64, 6


@dataclass(frozen=True)
class Axis:
    """``parts`` equal ranges of ``size`` ids, each cut in ``fine`` ranges of equal width between its least and greatest id in use."""

    size: int
    parts: int
    fine: int = 1
    lows: tuple[int, ...] = ()
    widths: tuple[int, ...] = ()

    @property
    def blocks(self) -> int:
        return self.parts * self.fine

    @property
    def longest(self) -> int:
        return -(-self.size // self.parts) if self.fine == 1 else max(self.widths)

    def corners(self) -> np.ndarray:
        """The first id of each block."""
        if self.fine == 1:
            return np.arange(self.parts, dtype=np.int64) * (-(-self.size // self.parts))
        return np.array([low + u * w for low, w in zip(self.lows, self.widths) for u in range(self.fine)], np.int64)

    def _at(self, values: tuple[int, ...], place: Column) -> Column:
        return F.get(F.array(*[F.lit(int(x)).cast("long") for x in values]), place.cast("int"))

    def block(self, column: str) -> Column:
        coarse = cut(column, self.size, self.parts)
        if self.fine == 1:
            return coarse
        within = F.call_function("div", F.col(column) - self._at(self.lows, coarse), self._at(self.widths, coarse))
        return coarse * self.fine + within

    def corner(self, block: str) -> Column:
        if self.fine == 1:
            return F.col(block) * F.lit(self.longest)
        part = F.call_function("div", F.col(block), F.lit(self.fine))
        return self._at(self.lows, part) + (F.col(block) - part * self.fine) * self._at(self.widths, part)

    def coarser(self, fine: int) -> Axis:
        """So many ranges for each part; lines of the coarser axis are lines of this one."""
        times = self.fine // fine
        return Axis(self.size, self.parts, fine, self.lows, tuple(w * times for w in self.widths))


def _in_use(size: int, parts: int, fine: int, *sides: tuple[SparseMatrix, str]) -> Axis:
    lows, highs = {}, {}
    for m, column in sides:
        for part, low, high in m.df.groupBy(cut(column, size, parts)).agg(F.min(column), F.max(column)).collect():  # a row for each part
            lows[part], highs[part] = min(low, lows.get(part, low)), max(high, highs.get(part, high))
    width = -(-size // parts)
    low = tuple(lows.get(p, p * width) for p in range(parts))
    return Axis(size, parts, fine, low, tuple(max(1, -(-(highs.get(p, low[p]) - low[p] + 1) // fine)) for p in range(parts)))


def _power(n: float) -> int:
    """The least power of two that is not below n."""
    return 1 << max(0, int(np.ceil(np.log2(max(n, 1)))))


def met_counts(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """One row: products, and entries of A and of B whose inner id the other has. Ids of both sides are counted together, so nothing is joined or sorted."""
    side = lambda m, k, x, y: m.df.select(F.col(k).alias("k"), F.lit(x).alias("x"), F.lit(y).alias("y")).filter(F.col("k").isNotNull())
    counts = side(a, "j", 1, 0).unionByName(side(b, "i", 0, 1)).groupBy("k").agg(F.sum("x").alias("da"), F.sum("y").alias("db"))
    return counts.filter((F.col("da") > 0) & (F.col("db") > 0)).agg(F.sum(F.col("da") * F.col("db").cast("double")), F.sum("da"), F.sum("db"))


def finer_axes(a: SparseMatrix, b: SparseMatrix, r: int, s: int, c: int, square: bool = False) -> tuple[tuple[Axis, Axis, Axis], bool]:
    """Axes of rows, inner ids and columns for a product on an r by s by c grid, and whether every entry is known to have a partner.

    Inner ranges are as fine as blocks of bounded size need. Cells get finer until they make few enough
    products, as long as the nonempty blocks do not have to be shipped too often for that. Three small
    tables of counts come to the driver.
    """
    plain = Axis(a.nrows, r), Axis(a.ncols, s), Axis(b.ncols, c)
    na, nb = a.df.count(), b.df.count()
    if na + nb <= SMALL_OPERANDS:
        return plain, False
    met = met_counts(a, b).first()
    products, whole = float(met[0] or 0), (met[1], met[2]) == (na, nb)
    inner = min(_power((na + nb) / INNER_ENTRIES / s), 4096)
    if square:
        line = _in_use(a.nrows, r, min(inner, _power(MOST_CELLS / r)), (a, "i"), (a, "j"))
        return (line, line, line), whole
    down = _in_use(a.nrows, r, _power(MOST_CELLS / r), (a, "i"))
    mid = _in_use(a.ncols, s, inner, (a, "j"), (b, "i"))
    along = _in_use(b.ncols, c, _power(MOST_CELLS / c), (b, "j"))
    count = lambda m, x, y: m.df.groupBy(x.block("i").alias("x"), y.block("j").alias("y")).count().collect()
    left, right = np.zeros((down.blocks, mid.blocks)), np.zeros((mid.blocks, along.blocks))
    for table, rows in ((left, count(a, down, mid)), (right, count(b, mid, along))):
        for x, y, n in rows:
            table[x, y] = n
    best = (1, 1)
    for cells in (1 << k for k in range(MOST_CELLS.bit_length())):
        f, g = (max(1, min(x.fine, _power(cells / x.parts))) for x in (down, along))
        x = left.reshape(down.parts * f, -1, mid.blocks).sum(1)
        y = right.reshape(mid.blocks, along.parts * g, -1).sum(2)
        ships = (x @ (y > 0)).sum() + ((x > 0) @ y).sum()
        if (f, g) != (1, 1) and ships > MOST_SHIPS * max(na + nb, 1):
            break
        best = (f, g)
        if products <= CELL_PRODUCTS * max(1, ((x > 0).astype(float) @ (y > 0) > 0).sum()):
            break
    return (down.coarser(best[0]), mid, along.coarser(best[1])), whole
