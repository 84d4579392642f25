"""SLAB: time bins divided, on each spatial axis by itself, into slabs.

A query whose grown box lies in one slab of an axis can take its candidates from that slab of its time
bins: each of them once, as an entry has one bin.  Of the axes that allow it, the one with the fewest
candidates is taken; a query that no axis serves falls back on the bins as they are, which stand among
the lists as an axis of their own: one schedule and one equi-join answer both kinds.
"""

from __future__ import annotations

import math
from typing import NamedTuple

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry
from ..functions.geometry import AXES
from ..session import materialize
from . import tally, timebins
from .index import BROADCAST_ROWS, ENTRY_ORDER, Extents, as_queries, dense_ids, entries_of, extents, other_trajectory, small

FALLBACK = -1


class Slabs(NamedTuple):
    v: int
    lo: tuple[float, ...]
    width: tuple[float, ...]

    def number(self, axis: int, x: Column) -> Column:
        """The slab of a coordinate, held inside; the same function for entries and queries, so overlapping ranges share a slab."""
        if self.width[axis] <= 0:
            return F.lit(0)
        return F.least(F.lit(self.v - 1), F.greatest(F.lit(0), F.floor((x - F.lit(self.lo[axis])) / F.lit(self.width[axis])).cast("int")))


def max_v(ext: Extents) -> int:
    """The most slabs such that, on every axis, no segment is larger than a slab."""
    limits = [math.floor((h - l) / s) for l, h, s in zip(ext.lo, ext.hi, ext.largest) if s > 0]
    return max(1, min(limits, default=1))


def grid(ext: Extents, v: int, check: str = "allow") -> Slabs:
    """``strict`` raises where a segment is larger than a slab, ``clamp`` lowers v until none is, ``allow`` takes v as it is."""
    if v < 1:
        raise ValueError("v is at least 1")
    if check not in ("strict", "clamp", "allow"):
        raise ValueError(check)
    if check != "allow" and v > max_v(ext):
        if check == "strict":
            raise ValueError(f"{v} slabs are smaller than the largest segment; at most {max_v(ext)}")
        v = max_v(ext)
    return Slabs(v, ext.lo, tuple((h - l) / v for l, h in zip(ext.lo, ext.hi)))


def lookup(binned: DataFrame, slabs: Slabs, whole: bool = False) -> DataFrame:
    """A row (axis, slab, bin and the entry) for each slab that an entry's extent touches, of all three axes.

    ``whole`` adds the entry under the axis FALLBACK, slab 0: its bin as it is."""
    def touched(axis: int, c: str) -> Column:
        span = F.sequence(slabs.number(axis, F.least(f"{c}0", f"{c}1")), slabs.number(axis, F.greatest(f"{c}0", f"{c}1")))
        return F.transform(span, lambda s: F.struct(F.lit(axis).alias("axis"), s.alias("slab")))

    lists = [touched(i, c) for i, c in enumerate(AXES)]
    if whole:
        lists.append(F.array(F.struct(F.lit(FALLBACK).alias("axis"), F.lit(0).alias("slab"))))
    return binned.withColumn("_s", F.explode(F.concat(*lists))).select("_s.axis", "_s.slab", *binned.columns)


def directory(look: DataFrame) -> DataFrame:
    """axis, slab, bin, lo, hi, n: where each list stands in the array of its axis, slab by slab and bin by bin.

    At most 3 m v rows; offsets come from the 3 v sums of the slabs, then from inside each slab."""
    n = materialize(look.groupBy("axis", "slab", "bin").agg(F.count(F.lit(1)).alias("n")))
    table, begin = [], {}
    for r in sorted(n.groupBy("axis", "slab").agg(F.sum("n").alias("n")).collect()):
        table.append((r.axis, r.slab, begin.get(r.axis, 0)))
        begin[r.axis] = begin.get(r.axis, 0) + r.n
    offsets = look.sparkSession.createDataFrame(table, "axis int, slab int, _begin long")
    ends = F.col("_begin") + F.sum("n").over(Window.partitionBy("axis", "slab").orderBy("bin"))
    return n.join(F.broadcast(offsets), ["axis", "slab"]).select("axis", "slab", "bin", (ends - F.col("n")).alias("lo"), (ends - 1).alias("hi"), "n")


def positions(look: DataFrame, dirs: DataFrame) -> DataFrame:
    """axis, pos, slab, bin, eid: the lookup arrays; needs ids."""
    w = Window.partitionBy("axis", "slab", "bin").orderBy("eid")
    return look.withColumn("_r", F.row_number().over(w) - 1).join(dirs.select("axis", "slab", "bin", "lo"), ["axis", "slab", "bin"]).select("axis", (F.col("lo") + F.col("_r")).alias("pos"), "slab", "bin", "eid")


class SlabIndex(NamedTuple):
    time: timebins.TimeBinIndex
    lookup: DataFrame
    directory: DataFrame
    slabs: Slabs
    lists: DataFrame | None = None  # the lookup with the bins as axis FALLBACK, laid out for searches
    by_bin: DataFrame | None = None  # the directory, a row for each bin


def build(d: DataFrame, m: int, v: int, check: str = "allow", ids: bool = False, block: int = timebins.BLOCK) -> SlabIndex:
    ext = extents(d)
    bins = timebins.Bins.of(ext, m)
    entries = timebins.assign(dense_ids(entries_of(d), ENTRY_ORDER) if ids else entries_of(d), bins)
    slabs = grid(ext, v, check)
    look = lookup(entries, slabs)
    time = timebins.TimeBinIndex(entries, timebins.directory(entries, bins), bins)
    if not time.directory.where(F.col("n") > block).isEmpty():
        time = time._replace(block=block)
    return SlabIndex(time, look, directory(look), slabs)


def _lists(index: SlabIndex) -> DataFrame:
    """Every list of the index; long ones are dealt over blocks by their counts."""
    if index.lists is not None:
        return index.lists
    rows = lookup(index.time.entries, index.slabs, whole=True)
    if not index.time.block:
        return rows
    every = index.directory.select("axis", "slab", "bin", "n").unionByName(index.time.directory.select(F.lit(FALLBACK).alias("axis"), F.lit(0).alias("slab"), "bin", "n"))
    hot = every.where(F.col("n") > index.time.block).select("axis", "slab", "bin", F.ceil(F.col("n") / index.time.block).cast("int").alias("_blocks"))
    keys = ["axis", "slab", "bin"]
    return rows.join(small(hot, 4 * index.time.bins.m * index.slabs.v), keys, "left").withColumn("block", timebins.block_of(F.coalesce("_blocks", F.lit(1)))).drop("_blocks")


def _keys(index: SlabIndex) -> list[str]:
    return ["axis", "slab", "bin"] + (["block"] if index.time.block else [])


def store(index: SlabIndex) -> SlabIndex:
    """The index with its lists laid out for searches, which then move queries only."""
    return index._replace(lists=timebins.in_place(_lists(index), _keys(index)), by_bin=materialize(_by_bin(index)))


def query_slabs(q: DataFrame, slabs: Slabs, dist: float | str) -> DataFrame:
    """Adds, for each axis, the first and last slab that the query's grown box touches."""
    for i, c in enumerate(AXES):
        a = slabs.number(i, F.least(f"q_{c}0", f"q_{c}1") - geometry.amount(dist))
        z = slabs.number(i, F.greatest(f"q_{c}0", f"q_{c}1") + geometry.amount(dist))
        q = q.withColumn(f"{c}a", a).withColumn(f"{c}z", z)
    return q


def _by_bin(index: SlabIndex) -> DataFrame:
    """The bins' directory with, for each axis, the counts of its slabs: a row for each bin."""
    if index.by_bin is not None:
        return index.by_bin
    counts = [F.map_from_entries(F.collect_list(F.when(F.col("axis") == i, F.struct("slab", "n")))).alias(f"s{c}") for i, c in enumerate(AXES)]
    return index.time.directory.join(small(index.directory.groupBy("bin").agg(*counts), 3 * index.time.bins.m * index.slabs.v), "bin", "left")


def _planned(q: DataFrame, index: SlabIndex, dist: float | str) -> DataFrame:
    """Each different query with _times, selector, slab, n_candidates, and lists: the bins it meets with their counts.

    Equal queries share a row, so that sums are taken once for each; the key of the one aggregate is the query
    itself, and what it is joined with before is bounded by m v."""
    qs = as_queries(q, dist)
    keys = qs.columns
    once = query_slabs(qs.groupBy(*keys).agg(F.count(F.lit(1)).alias("_times")), index.slabs, dist)
    met = timebins.overlaps(once, _by_bin(index), index.time.bins, keep=("n", "sx", "sy", "sz"))
    for c in AXES:
        # Only an axis on which the query keeps to one slab can serve it.
        met = met.withColumn(f"n{c}", F.when(F.col(f"{c}a") == F.col(f"{c}z"), F.coalesce(F.try_element_at(f"s{c}", f"{c}a"), F.lit(0).cast("long"))))
    sums = [F.sum("n").alias("all_n"), *(F.sum(f"n{c}").alias(f"n{c}") for c in AXES), F.collect_list(F.struct("bin", "n", "nx", "ny", "nz")).alias("lists")]
    counted = met.groupBy(*keys, "_times", *(f"{c}a" for c in AXES)).agg(*sums)
    choices = [F.when(F.col(f"n{c}").isNotNull(), F.struct(F.col(f"n{c}").alias("n"), F.lit(i).alias("axis"), F.col(f"{c}a").alias("slab"))) for i, c in enumerate(AXES)]
    best = counted.withColumn("_b", F.least(*choices))
    return best.select(*keys, "_times", F.coalesce("_b.axis", F.lit(FALLBACK)).alias("selector"), F.col("_b.slab").alias("slab"), F.coalesce("_b.n", "all_n").alias("n_candidates"), "lists")


def _again(df: DataFrame) -> DataFrame:
    """Equal queries as the rows they were."""
    return df.withColumn("_k", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_times")))).drop("_k", "_times")


def schedule(q: DataFrame, index: SlabIndex, dist: float | str) -> DataFrame:
    """Queries (prefixed) with selector (the axis, or FALLBACK), slab, and n_candidates; those that meet no bin are left out.

    The selector is the axis of fewest candidates among those with one slab; ties go to the first axis.  Counts come from sums over the
    directories, where these are small."""
    if not summed(index):
        return _again(_planned(q, index, dist).drop("lists"))
    v = index.slabs.v
    bins, lo, hi, n = timebins.bounds(index.time.directory)
    sums = tally.bin_sums(lo, hi, np.concatenate([n[None, :], _by_slab(index.directory, bins, v).reshape(3 * v, len(bins))]))
    qs = as_queries(q, dist)
    # Only an axis on which the query keeps to one slab can serve it.
    one = {c: F.col(f"{c}a") == F.col(f"{c}z") for c in AXES}
    asked = [F.when(one[c], 1 + i * v + F.col(f"{c}a")).otherwise(-1) for i, c in enumerate(AXES)]
    counted = query_slabs(qs, index.slabs, dist).withColumn("_n", sums("q_t0", "q_t1", F.lit(0), *asked)).where("_n.w > 0")
    best = counted.withColumn("_b", F.least(*(F.when(one[c], F.struct(F.col(f"_n.{c}").alias("n"), F.lit(i).alias("axis"), F.col(f"{c}a").alias("slab"))) for i, c in enumerate(AXES))))
    return best.select(*qs.columns, F.coalesce("_b.axis", F.lit(FALLBACK)).alias("selector"), F.col("_b.slab").alias("slab"), F.coalesce("_b.n", "_n.w").alias("n_candidates"))


def summed(index: SlabIndex) -> bool:
    """Whether the directories are small enough for every worker to hold their sums."""
    return 3 * index.time.bins.m * index.slabs.v <= BROADCAST_ROWS


def _by_slab(rows: DataFrame, bins: np.ndarray, v: int) -> np.ndarray:
    """Counts n of (axis, slab, bin) as an array of them, the bins at their places in ``bins``."""
    out, place = np.zeros((3, v, len(bins)), np.int64), {int(b): i for i, b in enumerate(bins)}
    for r in rows.select("axis", "slab", "bin", "n").collect():
        out[r.axis, r.slab, place[r.bin]] = r.n
    return out


def multi_counts(q: DataFrame, index: SlabIndex, dist: float | str) -> DataFrame:
    """Queries (prefixed) with the candidates of all slabs of the axis with the fewest: repeats, once for each common slab, and once.

    Slabs that two boxes share are one more than the faces between slabs that they share, so sums over the directory less
    those over faces count each pair once, and no pair is made."""
    v = index.slabs.v
    bins, lo, hi, _ = timebins.bounds(index.time.directory)

    def faces(axis: int, c: str) -> Column:
        a, z = index.slabs.number(axis, F.least(f"{c}0", f"{c}1")), index.slabs.number(axis, F.greatest(f"{c}0", f"{c}1"))
        return F.when(a < z, F.transform(F.sequence(a, z - 1), lambda s: F.struct(F.lit(axis).alias("axis"), s.alias("slab")))).otherwise(F.array())

    crossed = index.time.entries.select("bin", F.inline(F.concat(*(faces(i, c) for i, c in enumerate(AXES))))).groupBy("axis", "slab", "bin").agg(F.count(F.lit(1)).alias("n"))
    rows, cross = (np.concatenate([np.zeros((3, 1, len(bins)), np.int64), np.cumsum(_by_slab(f, bins, v), 1)], 1) for f in (index.directory, crossed))
    # Before slab s: rows[s], less the faces before it; up to slab s: rows[s + 1], less the same faces.
    weights = np.concatenate([rows, rows[:, :v] - cross[:, :v], rows[:, 1:] - cross[:, :v]], 1).reshape(3 * (3 * v + 1), len(bins))
    sums = tally.bin_sums(lo, hi, weights)
    qs = query_slabs(as_queries(q, dist), index.slabs, dist)
    s = qs.withColumn("_s", F.least(*(F.struct((F.col(f"{c}z") - F.col(f"{c}a")).alias("k"), F.lit(i).alias("axis"), F.col(f"{c}a").alias("a"), F.col(f"{c}z").alias("z")) for i, c in enumerate(AXES))))
    at = F.col("_s.axis") * (3 * v + 1)
    got = s.withColumn("_n", sums("q_t0", "q_t1", at + F.col("_s.a"), at + F.col("_s.z") + 1, at + v + 1 + F.col("_s.a"), at + 2 * v + 1 + F.col("_s.z")))
    return got.select(*as_queries(q, dist).columns, (F.col("_n.x") - F.col("_n.w")).alias("repeats"), (F.col("_n.z") - F.col("_n.y")).alias("once"))


def candidates(q: DataFrame, index: SlabIndex, dist: float | str) -> DataFrame:
    """Pairs before the time test: served queries from one slab, the others from their bins.  No pair arises twice."""
    plan = _planned(q, index, dist).drop("n_candidates")
    rows = plan.withColumn("_l", F.explode("lists")).drop("lists").withColumn("bin", F.col("_l.bin"))
    n = F.col("_l.n")
    for i, c in enumerate(AXES):
        n = F.when(F.col("selector") == i, F.col(f"_l.n{c}")).otherwise(n)
    rows = rows.withColumn("_n", n).where("_n > 0").withColumn("axis", F.col("selector")).withColumn("slab", F.coalesce("slab", F.lit(0)))
    rows = timebins.every_block(_again(rows), F.col("_n"), index.time.block).drop("_n", "_l")
    return timebins.meet(rows.drop("selector"), _lists(index), _keys(index)).drop("axis", "slab", "bin", "block")


def _shared(index: SlabIndex, dist: float | str) -> list[Column]:
    """For each axis, how many slabs a query and an entry share."""
    out = []
    for i, c in enumerate(AXES):
        lo, hi = (lambda f, p: f(f"{p}{c}0", f"{p}{c}1")), (lambda f, p: f(f"{p}{c}0", f"{p}{c}1"))
        a = F.greatest(index.slabs.number(i, lo(F.least, "")), index.slabs.number(i, lo(F.least, "q_") - geometry.amount(dist)))
        z = F.least(index.slabs.number(i, hi(F.greatest, "")), index.slabs.number(i, hi(F.greatest, "q_") + geometry.amount(dist)))
        out.append(F.greatest(z - a + 1, F.lit(0)).cast("long"))
    return out


def every_pair(q: DataFrame, index: SlabIndex, dist: float | str, mode: str) -> DataFrame:
    """Pairs with each list that both stand in: of all slabs of the axis with the fewest (``multi``), or of all axes (``intersect``).

    ``_arises`` is how often a pair is there."""
    qs = query_slabs(as_queries(q, dist), index.slabs, dist)
    spans = F.array(*(F.struct(F.lit(i).alias("axis"), F.col(f"{c}a").alias("a"), F.col(f"{c}z").alias("z")) for i, c in enumerate(AXES)))
    if mode == "multi":
        spans = F.array(F.array_min(F.transform(spans, lambda s: F.struct((s["z"] - s["a"]).alias("k"), s["axis"].alias("axis"), s["a"].alias("a"), s["z"].alias("z")))))
    elif mode != "intersect":
        raise ValueError(mode)
    rows = qs.withColumn("_s", F.explode(spans)).withColumn("axis", F.col("_s.axis")).withColumn("slab", F.explode(F.sequence("_s.a", "_s.z"))).drop("_s")
    met = timebins.overlaps(rows.drop(*(f"{c}{k}" for c in AXES for k in "az")), index.time.directory, index.time.bins, keep=())
    pairs = timebins.meet(met, index.lookup, ["axis", "slab", "bin"])
    x, y, z = _shared(index, dist)
    if mode == "multi":
        return pairs.withColumn("_arises", F.when(F.col("axis") == 0, x).when(F.col("axis") == 1, y).otherwise(z)).drop("slab", "bin")
    return pairs.withColumn("_arises", F.when((x > 0) & (y > 0) & (z > 0), x + y + z)).drop("slab", "bin")


def search(q: DataFrame, index: SlabIndex, dist: float | str, mode: str = "min", exclude_self: bool = True) -> DataFrame:
    """``min`` takes one slab of the best axis.  ``intersect`` takes entries that all three axes list, found as those whose
    lists of three axes hold the pair; ``multi`` takes all slabs of the axis with the fewest slabs, and removes what arises twice."""
    if mode == "min":
        pairs = candidates(q, index, dist)
        return geometry.matches(pairs.where(other_trajectory(exclude_self) & geometry.hints(dist)), dist)
    pairs = every_pair(q, index, dist, mode).where(other_trajectory(exclude_self))
    if mode == "multi":
        return geometry.repeated(geometry.matches(pairs.where(geometry.hints(dist)), dist, ("_arises",)), "_arises")
    keys = [c for c in pairs.columns if c not in ("axis", "_arises")]
    met = pairs.groupBy(*keys).agg(F.countDistinct("axis").alias("_axes"), F.count(F.lit(1)).alias("_n"), F.min("_arises").alias("_arises")).where("_axes = 3")
    met = met.withColumn("_k", F.explode(F.sequence(F.lit(1).cast("long"), F.expr("_n div _arises")))).drop("_axes", "_n", "_arises", "_k")
    return geometry.matches(met.where(geometry.hints(dist)), dist)


def totals(q: DataFrame, d: DataFrame, dist: float, m: int, choices: tuple[int, ...] = (1, 2, 4, 8, 16)) -> DataFrame:
    """v, candidates of the schedule of each choice.

    The bins are built once; for each v one aggregate over the entries makes its directory, and the schedule
    reads queries and directories only."""
    ext = extents(d)
    bins = timebins.Bins.of(ext, m)
    entries = timebins.assign(entries_of(d), bins)
    time, out = timebins.TimeBinIndex(entries, timebins.directory(entries, bins), bins), None
    for v in choices:
        slabs = grid(ext, v)
        look = lookup(entries, slabs)
        plan = schedule(q, SlabIndex(time, look, directory(look), slabs), dist)
        row = plan.agg(F.coalesce(F.sum("n_candidates"), F.lit(0)).cast("long").alias("candidates")).select(F.lit(v).alias("v"), "candidates")
        out = row if out is None else out.unionByName(row)
    return out


def choose_v(q: DataFrame, d: DataFrame, dist: float, m: int, choices: tuple[int, ...] = (1, 2, 4, 8, 16)) -> int:
    """The v whose schedule has the fewest candidates; ties go to the smallest."""
    return min((r.candidates, r.v) for r in totals(q, d, dist, m, choices).collect())[1]
