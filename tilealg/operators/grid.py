"""Partition grids: A (a x b) is cut in m by n pieces, B (b x c) in n by k."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class TileGrid:
    m: int
    n: int
    k: int
    a: int
    b: int
    c: int

    @classmethod
    def of(cls, a: int, b: int, c: int, m: int = 1, n: int = 1, k: int = 1) -> TileGrid:
        """Counts below 1 are an error; counts above an edge's length are held to it.  The last stripe may be short."""
        if min(m, n, k) < 1:
            raise ValueError("a grid needs at least one stripe on each edge")
        return cls(min(m, max(a, 1)), min(n, max(b, 1)), min(k, max(c, 1)), a, b, c)

    @staticmethod
    def _stripe(index: str, length: int, parts: int) -> Column:
        step = max(1, -(-length // parts))
        return F.least(F.expr(f"{index} div {step}"), F.lit(parts - 1)).cast("int")

    def alpha(self, row: str) -> Column:
        return self._stripe(row, self.a, self.m)

    def gamma(self, inner: str) -> Column:
        return self._stripe(inner, self.b, self.n)

    def beta(self, col: str) -> Column:
        return self._stripe(col, self.c, self.k)

    @property
    def products(self) -> int:
        return self.m * self.n * self.k
