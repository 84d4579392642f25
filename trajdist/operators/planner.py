"""Choosing a method by the number of candidates it would compare."""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry
from ..session import materialize
from . import cells, packed_tree, slabs, timebins
from .index import as_queries, extents, other_trajectory

#: A candidate reached through the tree costs so many candidates of a contiguous list.
TREE_COST = 3.0


class Indexes(NamedTuple):
    """The indexes that a method is chosen among; built once, read for every query set."""

    tbin: timebins.TimeBinIndex
    slab: slabs.SlabIndex
    tree: packed_tree.Tree
    cell: cells.CellIndex | None  # none where the grid is too fine for these segments


def prepare(d: DataFrame, m: int = 1000, v: int = 2, k: int = 20, r: int = 4) -> Indexes:
    d = materialize(d)
    try:
        cell = cells.build(d, k)
        cell = cell._replace(directory=materialize(cell.directory))
    except ValueError:
        cell = None
    return Indexes(timebins.build(d, m), slabs.build(d, m, v), packed_tree.build(d, r), cell)


def estimates(q: DataFrame, indexes: Indexes, dist: float) -> DataFrame:
    """method, candidates of each method: from directories and node boxes alone; entries are not read."""
    t = indexes.tbin
    parts = {
        "tbin": timebins.overlaps(as_queries(q), t.directory, t.bins).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("candidates")),
        "slab": slabs.schedule(q, indexes.slab, dist).agg(F.coalesce(F.sum("n_candidates"), F.lit(0)).alias("candidates")),
        "tree": packed_tree.frontiers(q, indexes.tree, dist)[-1].agg(F.coalesce(F.sum("n"), F.lit(0)).alias("candidates")),
    }
    if indexes.cell is not None:
        parts["cell"] = cells.demand(q, indexes.cell, dist).agg(F.coalesce(F.sum("demand"), F.lit(0)).alias("candidates"))
    out = None
    for name, p in parts.items():
        p = p.select(F.lit(name).alias("method"), F.col("candidates").cast("long").alias("candidates"))
        out = p if out is None else out.unionByName(p)
    return out


def cheapest(candidates: dict[str, int]) -> str:
    """The method of least cost: small and sparse data favour the tree, large distances the contiguous lists.  Ties go by name."""
    cost = {k: n * (TREE_COST if k == "tree" else 1.0) for k, n in candidates.items()}
    return min(cost, key=lambda k: (cost[k], k))


def recommend(q: DataFrame, d: DataFrame | Indexes, dist: float, **settings) -> str:
    indexes = d if isinstance(d, Indexes) else prepare(d, **settings)
    return cheapest({r["method"]: r["candidates"] for r in estimates(q, indexes, dist).collect()})


def hybrid(q: DataFrame, d: DataFrame, dist: float, m: int = 1000, r: int = 4, exclude_self: bool = True) -> DataFrame:
    """Each query by the cheaper of tree and time bins, as their candidate counts say."""
    q, d = materialize(q), materialize(d)
    tree, index = packed_tree.build(d, r), timebins.build(d, m)
    keys = ["q_traj_id", "q_seg_id"]
    by_tree = packed_tree.frontiers(q, tree, dist)[-1].groupBy(*keys).agg(F.sum("n").alias("tree_n"))
    by_bin = timebins.overlaps(as_queries(q), index.directory, index.bins).groupBy(*keys).agg(F.sum("n").alias("bin_n"))
    cheap = by_bin.join(by_tree, keys, "left").where(F.coalesce("tree_n", F.lit(0)) * TREE_COST <= F.col("bin_n")).select(F.col("q_traj_id").alias("traj_id"), F.col("q_seg_id").alias("seg_id"))
    cheap = materialize(cheap)
    one, other = q.join(cheap, ["traj_id", "seg_id"], "left_semi"), q.join(cheap, ["traj_id", "seg_id"], "left_anti")
    pairs = packed_tree.candidates(one, tree, dist).drop("leaf").unionByName(timebins.candidates(other, index).drop("bin", "block"))
    return geometry.matches(pairs.where(other_trajectory(exclude_self) & geometry.hints(dist)), dist)


def describe(d: DataFrame) -> dict:
    """What the choice of parameters starts from."""
    e = extents(d)
    return {"entries": e.n, "slab_cap": slabs.max_v(e), "longest_share_of_time": e.longest / (e.t_max - e.t_min) if e.t_max > e.t_min else 0.0}
