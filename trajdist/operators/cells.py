"""CELL: a uniform 3-D grid over space; entries and grown queries meet in shared cells."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace
from functools import cached_property

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry
from ..functions.geometry import AXES
from . import moving, tally
from .index import BROADCAST_ROWS, Extents, as_queries, entries_of, extents, other_trajectory
from .meeting import OWNED, Grid, Times, farthest, fitted, spread, wide
from .timebins import meet

#: Lookup rows for each entry that a grid may make.
REPLICATION = 500.0


def corners(df: DataFrame, grid: Grid, dist: float | str = 0.0, prefix: str = "") -> DataFrame:
    """Adds the lowest and highest cell of the box grown by ``dist``, by axis: xa, xz, ya, yz, za, zz (prefixed)."""
    for i, c in enumerate(AXES):
        a, b = F.col(f"{prefix}{c}0"), F.col(f"{prefix}{c}1")
        df = df.withColumn(f"{prefix}{c}a", grid.number(i, F.least(a, b) - geometry.amount(dist))).withColumn(f"{prefix}{c}z", grid.number(i, F.greatest(a, b) + geometry.amount(dist)))
    return df


def cells_touched(prefix: str = "") -> Column:
    sizes = [F.col(f"{prefix}{c}z") - F.col(f"{prefix}{c}a") + 1 for c in AXES]
    return sizes[0] * sizes[1] * sizes[2]


def of_box(df: DataFrame, grid: Grid, dist: float | str = 0.0, prefix: str = "") -> DataFrame:
    """A row (h) for each cell of each box."""
    out = corners(df, grid, dist, prefix)
    for c in AXES:
        out = out.withColumn(f"_c{c}", F.explode(F.sequence(f"{prefix}{c}a", f"{prefix}{c}z")))
    return out.withColumn("h", grid.linear(*(F.col(f"_c{c}") for c in AXES)))


_INNER = [f"_c{c}" for c in AXES]


def collapsed(d: DataFrame) -> DataFrame:
    """Segments that stay at their start for their whole time: each touches one cell."""
    for c in AXES:
        d = d.withColumn(f"{c}1", F.col(f"{c}0"))
    return d


def lookup(d: DataFrame, grid: Grid, limit: float = REPLICATION) -> DataFrame:
    """Entries with every cell h they touch.

    Counts the rows before making them, and refuses a grid that is too fine for the segments."""
    r = corners(d, grid).agg(F.count(F.lit(1)).alias("n"), F.sum(cells_touched()).alias("rows")).first()
    if r["n"] and r["rows"] > limit * r["n"]:
        raise ValueError(f"{r['rows']} cell entries for {r['n']} segments: the grid is too fine")
    return of_box(d, grid).drop(*_INNER)


def directory(look: DataFrame) -> DataFrame:
    """h, a_min, a_max, n of all cells that are not empty: where each stands in the lookup array."""
    n = look.groupBy("h").agg(F.count(F.lit(1)).alias("n"))
    # Offsets in two levels: runs of cells by the upper bits, then inside each run.
    run = n.withColumn("_r", F.shiftright("h", 12))
    sums = run.groupBy("_r").agg(F.sum("n").alias("_n"))
    got, begin, table = sorted(sums.collect()), 0, []
    for r in got:
        table.append((r["_r"], begin))
        begin += r["_n"]
    offsets = look.sparkSession.createDataFrame(table, "_r long, _begin long")
    ends = F.sum("n").over(Window.partitionBy("_r").orderBy("h"))
    return run.join(F.broadcast(offsets), "_r").select("h", (F.col("_begin") + ends - F.col("n")).alias("a_min"), (F.col("_begin") + ends - 1).alias("a_max"), "n")


@dataclass(frozen=True)
class CellIndex:
    lookup: DataFrame
    grid: Grid
    entries: DataFrame
    ext: Extents

    @cached_property
    def directory(self) -> DataFrame:
        return directory(self.lookup)


def build(d: DataFrame, nx: int, ny: int | None = None, nz: int | None = None, points: bool = False, limit: float = REPLICATION) -> CellIndex:
    """With ``points`` entries are taken as points that rest at their start."""
    d = collapsed(entries_of(d)) if points else entries_of(d)
    ext = extents(d)
    grid = Grid.of(ext, nx, ny, nz)
    look = lookup(d, grid, limit)
    return CellIndex(look, grid, d, ext)


def query_cells(q: DataFrame, index: CellIndex, dist: float | str) -> DataFrame:
    """Queries (prefixed) with each cell of their grown box that is not empty."""
    return of_box(as_queries(q, dist), index.grid, dist, "q_").drop(*_INNER).join(index.directory.select("h"), "h", "left_semi")


def candidates(q: DataFrame, index: CellIndex, dist: float | str) -> DataFrame:
    """Pairs by shared cell: a pair arises once for each cell that both touch, ``_arises`` times."""
    pairs = meet(query_cells(q, index, dist), index.lookup, ["h"])
    arises = F.lit(1).cast("long")
    for c in AXES:
        arises = arises * (F.least(f"q_{c}z", f"{c}z") - F.greatest(f"q_{c}a", f"{c}a") + 1)
    return pairs.withColumn("_arises", arises)


def owned(pairs: DataFrame, grid: Grid) -> DataFrame:
    """A pair only in the cell of the larger of the two low corners: once."""
    return pairs.where(F.col("h") == grid.linear(*(F.greatest(f"q_{c}a", f"{c}a") for c in AXES)))


def meeting(q: DataFrame, index: CellIndex, dist: float | str, once: bool = False) -> DataFrame:
    """Pairs by shared cell and shared part of time, in cells fitted to entries and to what queries reach: a pair arises once for each that
    both touch, and q_low and low tell which is its own.  ``once`` leaves repeats away on axes on which entries are wide."""
    grid, times = fitted(index.grid, index.ext, farthest(q, dist)), Times.of(index.ext)
    split = wide(index.entries, grid, times) if once else ""
    return meet(spread(as_queries(q, dist), grid, dist, "q_", times, split), spread(index.entries, grid, times=times, split=split), ["h", "_at"]).drop("h", "_at")


def search(q: DataFrame, index: CellIndex, dist: float | str, dedup: str = "owner", exclude_self: bool = True, rounded: bool = False) -> DataFrame:
    """A pair is kept in the cell of the larger of the two low corners, so nothing is shuffled to remove repeats.  ``late``
    compares every candidate and removes repeated results; ``early`` removes repeated candidates before they are compared;
    ``owner`` does not make them where entries touch many cells; where the mean entry is wider than a cell, both sides meet in
    cells while they are in them (``moving``), and a pair is kept where it first is within the distance.  ``rounded`` times have six places."""
    if dedup not in ("late", "early", "owner"):
        raise ValueError(dedup)
    if dedup == "owner" and exclude_self and not isinstance(dist, str) and 0 <= dist < math.inf and moving.crossing(index.grid, index.ext):
        return moving.search(q, index.entries, index.grid, index.ext, float(dist), rounded)
    pairs = meeting(q, index, dist, dedup == "owner").where(other_trajectory(exclude_self))
    if dedup == "late":
        found = geometry.matches(pairs.where(geometry.hints(dist)).withColumn("_own", F.expr(OWNED)), dist, ("_own",))
        found = found.where("_own").drop("_own")
    else:
        found = geometry.matches(pairs.where(OWNED).where(geometry.hints(dist)), dist)
    return found.withColumns({c: geometry.rounded(F.col(c)) for c in ("lo", "hi")}) if rounded else found


_CORNERS = [f"{c}{k}" for c in AXES for k in "az"]


def summed(index: CellIndex) -> bool:
    """Whether the grid is small enough for every worker to hold its sums."""
    return 8 * index.grid.n[0] * index.grid.n[1] * index.grid.n[2] <= BROADCAST_ROWS


def shared(q: DataFrame, index: CellIndex, dist: float) -> tuple[int, int]:
    """Candidates, once for each cell that both touch, and each once: from sums over the grid, no pair is made."""
    its = tally.cell_sums(corners(index.entries, index.grid), index.grid.n, tuple(_CORNERS))
    mine = tally.cell_sums(corners(as_queries(q), index.grid, dist, "q_"), index.grid.n, tuple(f"q_{c}" for c in _CORNERS))
    return tally.shared(mine, its)


def demand(q: DataFrame, index: CellIndex, dist: float | str) -> DataFrame:
    """q_traj, q_seg, demand: candidates of each query, from the directory alone (and the distance, where it is a column)."""
    more = [f"q_{dist}"] if isinstance(dist, str) else []
    if summed(index):
        sums = tally.box_sums(tally.cell_sums(corners(index.entries, index.grid), index.grid.n, tuple(_CORNERS))[::2, ::2, ::2])
        qs = corners(as_queries(q, dist), index.grid, dist, "q_").withColumn("n", sums(*(f"q_{c}" for c in _CORNERS)))
        return qs.groupBy(F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg"), *(F.col(c).alias(c.removeprefix("q_")) for c in more)).agg(F.sum("n").alias("demand"))
    met = of_box(as_queries(q, dist), index.grid, dist, "q_").select("q_traj_id", "q_seg_id", "h", *more).join(index.directory.select("h", "n"), "h", "left")
    return met.groupBy(F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg"), *(F.col(c).alias(c.removeprefix("q_")) for c in more)).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("demand"))


def chunk(index: CellIndex, i: int, of: int) -> CellIndex:
    """The share of the entries that pass ``i`` of a query looks at, where it needs more than the buffer holds."""
    mine = F.pmod(F.xxhash64("traj_id", "seg_id"), F.lit(of)) == i
    return replace(index, lookup=index.lookup.where(mine), entries=index.entries.where(mine)) if of > 1 else index
