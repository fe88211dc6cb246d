"""Semirings: how entries are added and multiplied, for Spark columns and for NumPy kernels."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """``add`` aggregates a column, ``mul`` joins two; ``np_add`` is a ufunc with reduceat, or none where values are not numbers."""

    name: str
    add: Callable[[Column], Column]
    mul: Callable[[Column, Column], Column]
    np_add: np.ufunc | None
    np_mul: Callable[[np.ndarray, np.ndarray], np.ndarray] | None
    sql_add: str
    sql_mul: str

    @property
    def numeric(self) -> bool:
        return self.np_add is not None


def _one(a: Column, b: Column) -> Column:
    return F.lit(1).cast("long")


SEMIRINGS: dict[str, Semiring] = {}


def register_semiring(s: Semiring) -> Semiring:
    SEMIRINGS[s.name] = s
    return s


_ones = lambda a, b: np.ones(len(a), np.int64)
for _name, _add, _mul, _na, _nm, _sa, _sm in (
    ("plus_times", F.sum, lambda a, b: a * b, np.add, np.multiply, "sum({})", "a.v * b.v"),
    ("plus_pair", F.sum, _one, np.add, _ones, "sum({})", "1"),
    ("or_and", F.max, _one, np.maximum, _ones, "max({})", "1"),
    ("min_plus", F.min, lambda a, b: a + b, np.minimum, np.add, "min({})", "a.v + b.v"),
    ("max_plus", F.max, lambda a, b: a + b, np.maximum, np.add, "max({})", "a.v + b.v"),
    ("max_min", F.max, F.least, np.maximum, np.minimum, "max({})", "least(a.v, b.v)"),
    ("min_max", F.min, F.greatest, np.minimum, np.maximum, "min({})", "greatest(a.v, b.v)"),
    ("max_times", F.max, lambda a, b: a * b, np.maximum, np.multiply, "max({})", "a.v * b.v"),
    ("min_first", F.min, lambda a, b: a, np.minimum, lambda a, b: a, "min({})", "a.v"),
    ("min_second", F.min, lambda a, b: b, np.minimum, lambda a, b: b, "min({})", "b.v"),
    ("xor_and", F.bit_xor, lambda a, b: a.bitwiseAND(b), np.bitwise_xor, np.bitwise_and, "bit_xor({})", "a.v & b.v"),
):
    register_semiring(Semiring(_name, _add, _mul, _na, _nm, _sa, _sm))

#: Values are (v, k): a length and the id through which it was reached; the least length wins, then the least id.
register_semiring(Semiring("argmin", F.min, lambda a, b: F.struct((a["v"] + b["v"]).alias("v"), a["k"].alias("k")), None, None, "min({})", ""))


def numeric_semirings() -> list[str]:
    return [name for name, s in SEMIRINGS.items() if s.numeric]


def semiring(name: str | Semiring) -> Semiring:
    return name if isinstance(name, Semiring) else SEMIRINGS[name]
