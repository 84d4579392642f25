"""Where queries and entries meet: cells of space, and parts of time.

A side has a row for each place its box touches, and its low corner on every axis marks one of them.  Two boxes that
share places share the one at the larger of their low corners, on each axis the low one of either: a pair is kept there
and nowhere else, without a look at other rows.  On a ``split`` axis that choice is part of the key, so the pair does
not even arise elsewhere; that pays where boxes span many places.
"""

from __future__ import annotations

import math
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import geometry
from ..functions.geometry import AXES
from .index import Extents

#: Most cells of an axis, and most parts of time.
MOST_CELLS, MOST_TIMES = 1024, 65_536
#: All low corners: of x, y, z and time.
ALL = 15


class Grid(NamedTuple):
    """Cells by axis; half-open, held inside at the faces."""

    n: tuple[int, int, int]
    lo: tuple[float, float, float]
    width: tuple[float, float, float]

    @classmethod
    def of(cls, ext: Extents, nx: int, ny: int | None = None, nz: int | None = None) -> "Grid":
        n = (nx, nx if ny is None else ny, nx if nz is None else nz)
        return cls(n, ext.lo, tuple((h - l) / k for l, h, k in zip(ext.lo, ext.hi, n)))

    def number(self, axis: int, x: Column) -> Column:
        if self.width[axis] <= 0:
            return F.lit(0).cast("long")
        return F.least(F.lit(self.n[axis] - 1), F.greatest(F.lit(0), F.floor((x - F.lit(self.lo[axis])) / F.lit(self.width[axis])))).cast("long")

    def linear(self, cx: Column, cy: Column, cz: Column) -> Column:
        """Row by row: the last axis runs fastest."""
        return (cx * self.n[1] + cy) * self.n[2] + cz


class Times(NamedTuple):
    """Parts of time, a power of two wide: so the part of a time is exact."""

    width: float
    first: int
    last: int

    @classmethod
    def of(cls, ext: Extents) -> "Times":
        """About as wide as the mean segment."""
        least = max(ext.mean[3], (ext.t_max - ext.t_min) / MOST_TIMES)
        width = 2.0 ** math.ceil(math.log2(least)) if least > 0 else 1.0
        return cls(width, math.floor(ext.t_min / width), max(math.floor(ext.t_min / width), math.ceil(ext.t_max / width) - 1))

    def held(self, part: Column) -> Column:
        return F.least(F.lit(self.last), F.greatest(F.lit(self.first), part)).cast("long")

    def range(self, t0: Column, t1: Column) -> tuple[Column, Column]:
        """The first and last part of a time that is open at its end; what overlaps for more than an instant shares one."""
        return self.held(F.floor(t0 / self.width)), self.held(F.ceil(t1 / self.width) - 1)


def fine(ext: Extents, dist: float) -> Grid:
    """Cells about as wide as a query reaches, on each axis that is long enough for them to leave entries out."""
    n = []
    for lo, hi, mean in zip(ext.lo, ext.hi, ext.mean):
        width = max(dist, 2 * mean)
        n.append(max(1, min(MOST_CELLS, int((hi - lo) / width))) if width > 0 and hi - lo > 1.5 * (2 * dist + mean + width) else 1)
    return Grid.of(ext, *n)


def fitted(grid: Grid, ext: Extents, dist: float) -> Grid:
    """The grid with each cell halved while it stays as wide as a query reaches, and cells put together where the mean entry is wider."""
    n = []
    for k, w, mean in zip(grid.n, grid.width, ext.mean):
        reach = max(dist, 2 * mean)
        if w > 0 and w < mean:
            k = max(1, math.floor(k * w / mean))
        elif w > 0 and reach > 0:
            while w >= 2 * reach and 2 * k <= MOST_CELLS:
                k, w = 2 * k, w / 2
        n.append(k)
    return Grid(tuple(n), grid.lo, tuple(w * k / m for w, k, m in zip(grid.width, grid.n, n)))


def farthest(q: DataFrame, dist: float | str) -> float:
    """The largest distance that is asked for."""
    return float(dist) if not isinstance(dist, str) else q.agg(F.max(dist)).first()[0] or 0.0


def spread(df: DataFrame, grid: Grid, dist: float | str = 0.0, prefix: str = "", times: Times | None = None, split: str = "") -> DataFrame:
    """A row for each place of each box: its cell h, its part of time and its choice on the split axes (_at), and the
    axes on which the place is the low one as bits of {prefix}low."""
    ranges = [(grid.number(i, F.least(f"{prefix}{c}0", f"{prefix}{c}1") - geometry.amount(dist)), grid.number(i, F.greatest(f"{prefix}{c}0", f"{prefix}{c}1") + geometry.amount(dist))) for i, c in enumerate(AXES)]
    ranges.append(times.range(F.col(f"{prefix}t0"), F.col(f"{prefix}t1")) if times else (F.lit(0).cast("long"),) * 2)
    columns, low, at = df.columns, F.lit(0), F.lit(0).cast("long")
    out = df.withColumns({f"_{c}a": a for c, (a, _) in zip("xyzt", ranges)} | {f"_{c}z": z for c, (_, z) in zip("xyzt", ranges)})
    for i, c in enumerate("xyzt"):
        if i == 3 and not times or i < 3 and grid.n[i] == 1:
            out = out.withColumn(f"_{c}", F.col(f"_{c}a"))
        else:
            out = out.withColumn(f"_{c}", F.explode(F.sequence(f"_{c}a", f"_{c}z")))
        first = F.col(f"_{c}") == F.col(f"_{c}a")
        low = low + F.when(first, 1 << i).otherwise(0)
        if c in split:
            # An entry has its own choice; a query goes to entries of either where its own place is the low one.
            if prefix:
                out = out.withColumn(f"_{c}s", F.explode(F.when(first, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(1)))))
            else:
                out = out.withColumn(f"_{c}s", first.cast("int"))
            at = at * 2 + F.col(f"_{c}s")
    at = F.col("_t") * (1 << len(split)) + at
    return out.select(*columns, grid.linear(*(F.col(f"_{c}") for c in AXES)).alias("h"), at.alias("_at"), low.cast("int").alias(f"{prefix}low"))


def wide(d: DataFrame, grid: Grid, times: Times) -> str:
    """The axes on which entries have more than one and a half places."""
    spans = [F.avg(grid.number(i, F.greatest(f"{c}0", f"{c}1")) - grid.number(i, F.least(f"{c}0", f"{c}1"))) for i, c in enumerate(AXES)]
    a, z = times.range(F.col("t0"), F.col("t1"))
    return "".join(c for c, more in zip("xyzt", d.agg(*spans, F.avg(z - a)).first()) if (more or 0) > 0.5)


#: A pair at the one place that keeps it.
OWNED = f"(q_low | low) = {ALL}"
