"""The plane in whole metres: a square world, its grid of square cells, closed rectangles."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Grid:
    """``2**bits`` by ``2**bits`` cells over a world of ``side`` metres."""

    side: int
    bits: int = 6

    @property
    def n(self) -> int:
        return 1 << self.bits

    @property
    def cell_side(self) -> int:
        return -(-self.side // self.n)

    def axis(self, v: Column) -> Column:
        """Number of the column or row that a coordinate lies in; coordinates off the world go to its border."""
        return F.least(F.greatest(F.floor(v / self.cell_side), F.lit(0)), F.lit(self.n - 1)).cast("int")

    def cell(self, x: Column, y: Column) -> Column:
        return (self.axis(y) * self.n + self.axis(x)).cast("int")

    def overlapped(self, x0: Column, y0: Column, x1: Column, y1: Column) -> Column:
        """Array of the cells that a closed rectangle has a point in, borders of the world included."""
        xs = F.sequence(self.axis(x0), self.axis(x1))
        ys = F.sequence(self.axis(y0), self.axis(y1))
        return F.flatten(F.transform(ys, lambda cy: F.transform(xs, lambda cx: cy * self.n + cx)))


def inside(x: Column, y: Column, x0: Column, y0: Column, x1: Column, y1: Column) -> Column:
    """Whether a point lies in a closed rectangle."""
    return (x >= x0) & (x <= x1) & (y >= y0) & (y <= y1)
