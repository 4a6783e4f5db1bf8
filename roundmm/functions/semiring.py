"""Semirings, as Catalyst expressions and as NumPy kernels."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """``plus`` aggregates a column, ``times`` joins two; ``zero`` fills missing cells, ``one`` is the unit of times."""

    name: str
    zero: float
    one: float
    plus: Callable[[Column], Column]
    times: Callable[[Column, Column], Column]
    merge: np.ufunc
    pair: np.ufunc
    sql_plus: str
    sql_times: str

    def combine(self, a: Column, b: Column) -> Column:
        """``a`` plus ``b`` of single cells; a null is the zero."""
        zero = F.lit(self.zero)
        a, b = F.coalesce(a, zero), F.coalesce(b, zero)
        return {"min": F.least, "max": F.greatest}.get(self.sql_plus, lambda x, y: x + y)(a, b)

    def product(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Dense block product; BLAS where the semiring is the ordinary one."""
        if self.merge is np.add and self.pair is np.multiply:
            return a @ b
        out = np.full((a.shape[0], b.shape[1]), self.zero)
        for k in range(a.shape[1]):
            self.merge(out, self.pair(a[:, k, None], b[None, k, :]), out=out)
        return out


INF = float("inf")
PLUS_TIMES = Semiring("plus_times", 0.0, 1.0, F.sum, lambda a, b: a * b, np.add, np.multiply, "sum", "{a} * {b}")
COUNT = Semiring("count", 0.0, 1.0, F.sum, lambda a, b: a * b, np.add, np.multiply, "sum", "{a} * {b}")
MIN_PLUS = Semiring("min_plus", INF, 0.0, F.min, lambda a, b: a + b, np.minimum, np.add, "min", "{a} + {b}")
MAX_PLUS = Semiring("max_plus", -INF, 0.0, F.max, lambda a, b: a + b, np.maximum, np.add, "max", "{a} + {b}")
MAX_MIN = Semiring("max_min", -INF, INF, F.max, F.least, np.maximum, np.minimum, "max", "least({a}, {b})")
#: On values of at least zero only.
MAX_TIMES = Semiring("max_times", 0.0, 1.0, F.max, lambda a, b: a * b, np.maximum, np.multiply, "max", "{a} * {b}")
#: On zeros and ones.
OR_AND = Semiring("or_and", 0.0, 1.0, F.max, F.least, np.maximum, np.minimum, "max", "least({a}, {b})")

SEMIRINGS = {s.name: s for s in (PLUS_TIMES, COUNT, MIN_PLUS, MAX_PLUS, MAX_MIN, MAX_TIMES, OR_AND)}
