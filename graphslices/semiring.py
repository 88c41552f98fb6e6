"""The four semirings of traversal: one definition as Spark columns, one as NumPy, and what each costs beside the product."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from graphslices.schema import INF


@dataclass(frozen=True)
class Semiring:
    """plus is associative and commutative with the identity zero; edge gives what a neighbour's value brings along an edge (times the edge's value)."""

    name: str
    zero: float
    one: float
    edge_value: float
    pad_value: float
    aggregate: Callable[[Column], Column]
    edge: Callable[[Column], Column]
    np_plus: np.ufunc
    np_edge: Callable[[np.ndarray], np.ndarray]
    dtype: type
    sql_type: str
    post_ops: int
    post_stores: int
    gives_parents: bool = False

    def times(self, a: float, b: float) -> float:
        """The product of two values of the carrier."""
        if self.name == "tropical":
            return min(a + b, INF)
        return min(a, b) if self.name == "boolean" else a * b

    def plus(self, a: float, b: float) -> float:
        return {"tropical": min, "boolean": max, "selmax": max}.get(self.name, lambda x, y: x + y)(a, b)


def _near(x: np.ndarray) -> np.ndarray:
    return np.where(x >= INF, INF, x + 1)


TROPICAL = Semiring(
    "tropical", INF, 0, 1, INF, F.min, lambda x: F.when(x >= INF, F.lit(INF).cast("long")).otherwise(x + 1), np.minimum, _near, np.int64, "bigint", 0, 0,
)
REAL = Semiring("real", 0, 1, 1, 0, F.sum, lambda x: x, np.add, lambda x: x, np.float64, "double", 6, 2)
BOOLEAN = Semiring("boolean", 0, 1, 1, 0, F.max, lambda x: x, np.maximum, lambda x: x, np.int64, "bigint", 6, 2)
SELMAX = Semiring("selmax", 0, 1, 1, 0, F.max, lambda x: x, np.maximum, lambda x: x, np.int64, "bigint", 4, 2, True)
SEMIRINGS = {s.name: s for s in (TROPICAL, REAL, BOOLEAN, SELMAX)}
