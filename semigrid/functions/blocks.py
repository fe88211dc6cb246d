"""Doubly compressed blocks: pointers for nonempty columns alone, as arrays in one row of a table.

A block keeps the ids of its nonempty columns, where each column begins, and the row ids
and values in column order. The same four arrays of the transpose are the row form. Ids
count from the block's own corner, so nothing in a block depends on the matrix dimension.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import types as T

Triples = tuple[np.ndarray, np.ndarray, np.ndarray]

#: Value types that blocks hold, with their arrays.
VALUES: dict[type, tuple[np.dtype, pa.DataType]] = {
    T.LongType: (np.dtype(np.int64), pa.int64()),
    T.IntegerType: (np.dtype(np.int32), pa.int32()),
    T.DoubleType: (np.dtype(np.float64), pa.float64()),
    T.FloatType: (np.dtype(np.float32), pa.float32()),
}


def value_arrays(kind: T.DataType) -> tuple[np.dtype, pa.DataType]:
    if type(kind) not in VALUES:
        raise TypeError(f"blocks hold numbers, not {kind.simpleString()}; use the relational product")
    return VALUES[type(kind)]


@dataclass(frozen=True)
class Block:
    """Nonempty major ids, pointers (one more than ids), minor ids and values."""

    ids: np.ndarray
    start: np.ndarray
    minor: np.ndarray
    num: np.ndarray

    @property
    def nnz(self) -> int:
        return len(self.minor)

    def major(self) -> np.ndarray:
        """The major id of each entry."""
        return np.repeat(self.ids, np.diff(self.start))

    def turned(self) -> Block:
        """The block with the other orientation: the transposition that is done once and kept."""
        return pack(self.minor, self.major(), self.num)


def pack(major: np.ndarray, minor: np.ndarray, num: np.ndarray) -> Block:
    """From entries in any order: columns as ``major`` give the column form, rows the row form."""
    order = np.lexsort((minor, major))
    major = major[order]
    head = np.flatnonzero(np.r_[True, major[1:] != major[:-1]]) if len(major) else np.zeros(0, np.int64)
    return Block(major[head].astype(np.int64), np.r_[head, len(major)].astype(np.int64), minor[order].astype(np.int64), num[order])


def columns_of(t: Triples) -> Block:
    return pack(t[1], t[0], t[2])


def rows_of(t: Triples) -> Block:
    return pack(t[0], t[1], t[2])


def triples_of_columns(b: Block) -> Triples:
    return b.minor, b.major(), b.num


def triples_of_rows(b: Block) -> Triples:
    return b.major(), b.minor, b.num


class ColumnIndex:
    """Finds a nonempty id in about constant time: the ids are cut in as many chunks as there are nonempty ones."""

    def __init__(self, block: Block, n: int):
        self.block, self.width = block, max(1, -(-n // max(1, len(block.ids))))
        self.first = np.searchsorted(block.ids, np.arange(0, n + self.width, self.width))

    def entries(self, j: int) -> tuple[np.ndarray, np.ndarray]:
        """Minor ids and values of column (or row) ``j``."""
        b, chunk = self.block, j // self.width
        for k in range(self.first[chunk], self.first[chunk + 1]):
            if b.ids[k] == j:
                return b.minor[b.start[k] : b.start[k + 1]], b.num[b.start[k] : b.start[k + 1]]
        return b.minor[:0], b.num[:0]


FIELDS = ("ids", "start", "minor", "num")


def block_columns(value: pa.DataType, prefix: str = "") -> list[tuple[str, pa.DataType]]:
    return [(f"{prefix}ids", pa.list_(pa.int64())), (f"{prefix}start", pa.list_(pa.int64())), (f"{prefix}minor", pa.list_(pa.int64())), (f"{prefix}num", pa.list_(value))]


def block_schema(kind: T.DataType, prefix: str = "") -> str:
    return ", ".join(f"{prefix}{f} array<{kind.simpleString() if f == 'num' else 'bigint'}>" for f in FIELDS)


def block_arrays(block: Block, value: pa.DataType) -> list[pa.Array]:
    """One row of the four array columns."""
    one = lambda x, t: pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), pa.array(x, t))
    return [one(block.ids, pa.int64()), one(block.start, pa.int64()), one(block.minor, pa.int64()), one(block.num, value)]


#: Types of the arrays of a block that is one value; whole numbers first, by their bytes.
_KINDS = [np.dtype(x) for x in (np.int8, np.int16, np.int32, np.int64, np.float32, np.float64)]


def _narrow(x: np.ndarray) -> np.ndarray:
    """Whole numbers in the fewest bytes that hold them all."""
    if x.dtype.kind != "i":
        return x
    low, high = (int(x.min()), int(x.max())) if len(x) else (0, 0)
    return x.astype(next(t for t in _KINDS if np.iinfo(t).min <= low and high <= np.iinfo(t).max))


def block_value(block: Block) -> bytes:
    """The block as one binary value: the kind and length of each array, the kind of the values, then the arrays."""
    arrays = [_narrow(x) for x in (block.ids, block.start, block.minor, block.num)]
    head = [n for x in arrays for n in (_KINDS.index(x.dtype), len(x))] + [_KINDS.index(block.num.dtype)]
    return b"".join([np.array(head, np.int64).tobytes(), *(x.tobytes() for x in arrays)])


def block_of_value(value: pa.Buffer | bytes) -> Block:
    head, at, arrays = np.frombuffer(value, np.int64, 9).tolist(), 72, []
    for kind, n in zip(head[0:8:2], head[1:8:2]):
        arrays.append(np.frombuffer(value, _KINDS[kind], n, at))
        at += arrays[-1].nbytes
    return Block(*(x.astype(np.int64) for x in arrays[:3]), arrays[3].astype(_KINDS[head[8]]))


def read_block(batch: pa.RecordBatch, row: int, first: int) -> Block:
    """The block in four columns of a batch, from column ``first`` on; no value is copied."""
    return Block(*(batch.column(first + k)[row].values.to_numpy(zero_copy_only=False) for k in range(4)))
