"""TREE: a packed R-tree over boxes in space and time, the baseline.

``r`` consecutive segments of a trajectory share a leaf box.  Leaves are packed by slices of time, then of
each spatial axis; every level has one node for ``fanout`` of the level below.  Levels above the leaves are a
fraction of them and are broadcast while that is small; queries meet larger ones by a shuffle on the parent.
"""

from __future__ import annotations

import math
from typing import NamedTuple

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry
from ..functions.geometry import AXES
from ..session import materialize
from . import tally, timebins
from .index import as_queries, by_trajectory, dense_ids, entries_of, other_trajectory, small

BOX = [f"{c}{k}" for c in "txyz" for k in ("lo", "hi")]


def leaves(d: DataFrame, r: int) -> DataFrame:
    """traj_id, leaf and the box of each run of r segments."""
    members = with_leaf(d, r)
    aggs = [F.min("t0").alias("tlo"), F.max("t1").alias("thi")]
    for c in AXES:
        aggs += [F.min(F.least(f"{c}0", f"{c}1")).alias(f"{c}lo"), F.max(F.greatest(f"{c}0", f"{c}1")).alias(f"{c}hi")]
    return members.groupBy("traj_id", "leaf").agg(*aggs, F.count(F.lit(1)).alias("n"))


def with_leaf(d: DataFrame, r: int) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("traj_id").orderBy("seg_id")) - 1
    return entries_of(d).withColumn("leaf", F.floor(rank / r).cast("long"))


def _sliced(df: DataFrame, slices: int) -> DataFrame:
    """The slices of a box's middle, in t, x and y, between approximate quantiles: one pass, at most 3 (slices - 1) bounds."""
    mids = {c: F.expr(f"({c}lo + {c}hi) / 2") for c in "txy"}
    cuts = df.select(*(m.alias(c) for c, m in mids.items())).approxQuantile(list(mids), [i / slices for i in range(1, slices)], 0.01) if slices > 1 else [[]] * 3
    return df.withColumns({f"_s{c}": sum(((m > F.lit(b)).cast("int") for b in bounds), F.lit(0)) for (c, m), bounds in zip(mids.items(), cuts)})


class Tree(NamedTuple):
    levels: list[DataFrame]  # from the root's children down to the leaves: node, parent, box
    entries: DataFrame  # segments with leaf
    fanout: int
    sizes: list[int]  # nodes of each level


def build(d: DataFrame, r: int, fanout: int = 16) -> Tree:
    boxes = materialize(leaves(d, r))
    n = boxes.count()
    slices = max(1, math.ceil((n / fanout) ** 0.25))
    order = ["_st", "_sx", "_sy", "zlo", "tlo", "traj_id", "leaf"]
    level = dense_ids(_sliced(boxes, slices), order, "node").drop("_st", "_sx", "_sy")
    levels, sizes = [materialize(level.withColumn("parent", F.expr(f"node div {fanout}")))], [n]
    while n > 1:
        n = math.ceil(n / fanout)
        up = levels[0].groupBy(F.col("parent").alias("node")).agg(*(F.min(b).alias(b) if b.endswith("lo") else F.max(b).alias(b) for b in BOX))
        levels.insert(0, materialize(up.withColumn("parent", F.expr(f"node div {fanout}"))))
        sizes.insert(0, n)
    return Tree(levels, with_leaf(d, r), fanout, sizes)


def store(tree: Tree) -> Tree:
    """The tree with its entries laid out by leaf."""
    return tree._replace(entries=timebins.in_place(tree.entries, ["traj_id", "leaf"]))


def _meets() -> Column:
    """A node's box against the query's box, grown in space only."""
    keep = (F.col("tlo") < F.col("_t1")) & (F.col("_t0") < F.col("thi"))
    for c in AXES:
        keep &= (F.col(f"{c}lo") <= F.col(f"_{c}1")) & (F.col(f"{c}hi") >= F.col(f"_{c}0"))
    return keep


def frontiers(q: DataFrame, tree: Tree, dist: float | str) -> list[DataFrame]:
    """The visited nodes of each level: queries with node; for leaves also traj_id, leaf and their number of members n.

    A query goes down as its box and one struct of its columns: so the levels together stay a method that the
    virtual machine compiles."""
    qs = as_queries(q, dist)
    boxes = {"_t0": F.col("q_t0"), "_t1": F.col("q_t1")}
    for c in AXES:
        boxes |= {f"_{c}0": F.least(f"q_{c}0", f"q_{c}1") - geometry.amount(dist), f"_{c}1": F.greatest(f"q_{c}0", f"q_{c}1") + geometry.amount(dist)}
    now = qs.select(F.struct(*qs.columns).alias("_q"), *(e.alias(c) for c, e in boxes.items()), F.lit(0).cast("long").alias("_at"))
    out = []
    for level, size in zip(tree.levels, tree.sizes):
        met = now.join(small(level.withColumnRenamed("parent", "_at"), size), "_at").where(_meets()).drop("_at", *BOX)
        out.append(met.select("_q.*", *(c for c in met.columns if c != "_q" and c not in boxes)))
        now = met.drop("traj_id", "leaf", "n").withColumnRenamed("node", "_at")
    return out


def demand(q: DataFrame, boxes: DataFrame, r: int, dist: float | str) -> DataFrame:
    """q_traj_id, q_seg_id (and the distance, where it is a column) and n: members of the ``leaves`` of up to r that a query reaches, counted as
    bits; queries that reach none are left out."""
    keys = ["q_traj_id", "q_seg_id", *([f"q_{dist}"] if isinstance(dist, str) else [])]
    ranges = {f"q_{c}_lo": F.least(f"q_{c}0", f"q_{c}1") - geometry.amount(dist) for c in AXES} | {f"q_{c}_hi": F.greatest(f"q_{c}0", f"q_{c}1") + geometry.amount(dist) for c in AXES}
    qs = as_queries(q, dist).select(*keys, "q_t0", "q_t1", *(e.alias(k) for k, e in ranges.items()), F.xxhash64(*keys).alias("_q"))
    held = boxes.select(F.col("tlo").alias("t0"), F.col("thi").alias("t1"), *(F.col(f"{c}{k}").alias(f"{c}_{k}") for c in AXES for k in ("lo", "hi")), "n", F.xxhash64("traj_id", "leaf").alias("_e"))
    return tally.counts(qs, held, {"n": (tuple(AXES), ())}, r, tuple(keys))


def candidates(q: DataFrame, tree: Tree, dist: float | str) -> DataFrame:
    """Pairs of queries and the members of the leaves they reach."""
    return timebins.meet(frontiers(q, tree, dist)[-1].drop("node", "n"), tree.entries, ["traj_id", "leaf"])


def search(q: DataFrame, tree: Tree, dist: float | str, exclude_self: bool = True, tasks: int | None = None) -> DataFrame:
    """``tasks`` deals queries by trajectory over so many tasks, each of which goes down the tree for its own."""
    pairs = candidates(by_trajectory(q, tasks) if tasks else q, tree, dist)
    return geometry.matches(pairs.where(other_trajectory(exclude_self) & geometry.hints(dist)), dist)


def visited(q: DataFrame, tree: Tree, dist: float | str) -> DataFrame:
    """level, nodes: how many nodes queries visit."""
    parts = [f.agg(F.count(F.lit(1)).alias("nodes")).withColumn("level", F.lit(i)) for i, f in enumerate(frontiers(q, tree, dist))]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.select("level", "nodes")


#: Entries of a local leaf, and pairs that a task of the local search looks at together.
LOCAL_LEAF, LOCAL_PAIRS = 32, 1 << 20


def search_local(q: DataFrame, d: DataFrame, dist: float, parts: int = 64, exclude_self: bool = True, block: int = 200_000) -> DataFrame:
    """Two tiers: time bins route queries to parts of the entries, each of which packs a tree of its own.

    A part holds at most about ``block`` entries (a fuller bin is dealt over several).  Its entries are sorted by slices of time,
    then x, into leaves; queries meet the leaves' boxes, and the members of those they reach, in blocks of bounded size."""
    index = timebins.build(d, parts, block=block)
    keys = timebins.keys_of(index)
    met = timebins.overlaps(as_queries(q), index.directory, index.bins, keep=("n",))
    routed = timebins.every_block(met, F.col("n"), index.block).drop("n")
    names = [c for c in routed.columns + index.entries.columns if c not in keys]
    kinds = dict(routed.dtypes + index.entries.dtypes)

    def meet(_key, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        import numpy as np

        left, right = left.drop(columns=keys), right.drop(columns=keys)
        empty = pd.concat([left.iloc[:0], right.iloc[:0]], axis=1)[names]
        if not len(left) or not len(right):
            return empty
        n = len(right)
        leaves_n = -(-n // LOCAL_LEAF)
        by_time = np.argsort(right.t0.to_numpy(), kind="stable")
        slice_of = np.empty(n, np.int64)
        slice_of[by_time] = np.arange(n) * max(1, round(leaves_n**0.5)) // n
        right = right.iloc[np.lexsort((right.x0.to_numpy(), slice_of))].reset_index(drop=True)
        cuts = np.arange(0, n, LOCAL_LEAF)

        def box(frame: pd.DataFrame, prefix: str, grow: float) -> list[tuple]:
            ends = [(frame[f"{prefix}{c}0"].to_numpy(), frame[f"{prefix}{c}1"].to_numpy()) for c in "txyz"]
            return [(np.minimum(a, b) - (grow if i else 0), np.maximum(a, b) + (grow if i else 0)) for i, (a, b) in enumerate(ends)]

        def touch(a: list[tuple], b: list[tuple], i, j) -> np.ndarray:
            keep = (a[0][0][i] < b[0][1][j]) & (b[0][0][j] < a[0][1][i])
            for (lo, hi), (low, high) in zip(a[1:], b[1:]):
                keep &= (lo[i] <= high[j]) & (low[j] <= hi[i])
            return keep

        asked, held = box(left, "q_", dist), box(right, "", 0.0)
        packed = [(np.minimum.reduceat(lo, cuts), np.maximum.reduceat(hi, cuts)) for lo, hi in held]
        found_i, found_j = [], []
        step = max(1, LOCAL_PAIRS // leaves_n)
        for a in range(0, len(left), step):
            rows = np.arange(a, min(a + step, len(left)))[:, None]
            i, leaf = np.nonzero(touch(asked, packed, rows, np.arange(leaves_n)[None, :]))
            for b in range(0, len(i), LOCAL_PAIRS // LOCAL_LEAF):
                at, lf = np.repeat(i[b : b + LOCAL_PAIRS // LOCAL_LEAF] + a, LOCAL_LEAF), leaf[b : b + LOCAL_PAIRS // LOCAL_LEAF]
                member = (lf[:, None] * LOCAL_LEAF + np.arange(LOCAL_LEAF)[None, :]).ravel()
                inside = member < n
                at, member = at[inside], member[inside]
                keep = touch(asked, held, at, member)
                found_i.append(at[keep])
                found_j.append(member[keep])
        if not found_i:
            return empty
        i, j = np.concatenate(found_i), np.concatenate(found_j)
        return pd.concat([left.iloc[i].reset_index(drop=True), right.iloc[j].reset_index(drop=True)], axis=1)[names]

    pairs = routed.groupBy(*keys).cogroup(index.entries.groupBy(*keys)).applyInPandas(meet, ", ".join(f"{c} {kinds[c]}" for c in names))
    return geometry.matches(pairs.where(other_trajectory(exclude_self)), dist)
