"""One entry point for all methods, and answers about whole trajectories."""

from __future__ import annotations

from pyspark.sql import DataFrame, Row, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry
from ..session import materialize
from ..sources.tables import load_by_time
from . import brute, cells, packed_tree, slabs, timebins
from .index import as_queries, other_trajectory

METHODS = ("brute", "cell", "tbin", "slab", "tree")


def run(q: DataFrame, d: DataFrame, dist: float, method: str = "tbin", exclude_self: bool = True, m: int = 1000, v: int = 2, nx: int = 20, r: int = 4, **options) -> DataFrame:
    """All (query segment, entry segment) pairs within ``dist``, with the time interval of each."""
    if method == "brute":
        return brute.search(q, d, dist, exclude_self)
    if method == "tbin":
        return timebins.search(q, timebins.build(d, m, ids=options.get("mode") == "range"), dist, exclude_self=exclude_self, **options)
    if method == "slab":
        return slabs.search(q, slabs.build(d, m, v), dist, exclude_self=exclude_self, **options)
    if method == "cell":
        return cells.search(q, cells.build(d, nx), dist, exclude_self=exclude_self, **options)
    if method == "tree":
        return packed_tree.search(q, packed_tree.build(d, r), dist, exclude_self=exclude_self, **options)
    raise ValueError(method)


def contacts(matches: DataFrame) -> DataFrame:
    """q_traj, traj_id, lo, hi: overlapping or touching intervals of each pair of trajectories, merged."""
    w = Window.partitionBy("q_traj", "traj_id").orderBy("lo", "hi")
    before = F.max("hi").over(w.rowsBetween(Window.unboundedPreceding, -1))
    flagged = matches.withColumn("_new", F.when(F.col("lo") <= before, 0).otherwise(1))
    island = flagged.withColumn("_k", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return island.groupBy("q_traj", "traj_id", "_k").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).drop("_k")


def trajectories_within(q: DataFrame, d: DataFrame, dist: float, ts: float, te: float, mode: str = "any", tolerance: float = 1e-9, **how) -> DataFrame:
    """q_traj, traj_id of trajectories within ``dist`` at any time of [ts, te], or (``always``) at all of it.

    Both sides are cut to the interval first."""
    found = run(geometry.clip(q, ts, te), geometry.clip(d, ts, te), dist, **how)
    if mode == "any":
        return found.select("q_traj", "traj_id").distinct()
    covered = contacts(found).groupBy("q_traj", "traj_id").agg(F.sum(F.col("hi") - F.col("lo")).alias("covered"))
    return covered.where(F.col("covered") >= te - ts - tolerance).select("q_traj", "traj_id")


def fixed_point(spark: SparkSession, x: float, y: float, z: float, ts: float, te: float, traj_id: int = -1) -> DataFrame:
    """A place that does not move, over an interval, as a query."""
    return spark.range(1).select(
        F.lit(traj_id).cast("long").alias("traj_id"), F.lit(0).cast("long").alias("seg_id"), F.lit(float(ts)).alias("t0"), *(F.lit(float(c)).alias(f"{a}0") for a, c in zip("xyz", (x, y, z))),
        F.lit(float(te)).alias("t1"), *(F.lit(float(c)).alias(f"{a}1") for a, c in zip("xyz", (x, y, z))),
    )


def self_join(d: DataFrame, dist: float, ordered: bool = False, **how) -> DataFrame:
    """Every trajectory against all others; each pair once unless ``ordered``."""
    found = run(d, d, dist, **how)
    return found if ordered else found.where("q_traj < traj_id")


def nearest(q: DataFrame, d: DataFrame, k: int, start: float, m: int = 100) -> DataFrame:
    """The k trajectories that come nearest to each query trajectory: q_traj, traj_id, d_min, t_min.

    The radius doubles for the queries that still lack k; answers within it are final.  It ends at the diagonal of all
    positions, where each query has met every trajectory that shares time with it.  Ties go to the smaller id."""
    index, pending, dist, done = timebins.build(d, m), q, start, []
    lo, hi = zip(*(q.unionByName(d, allowMissingColumns=True).agg(F.min(F.least(f"{c}0", f"{c}1")), F.max(F.greatest(f"{c}0", f"{c}1"))).first() for c in "xyz"))
    limit = sum((b - a) ** 2 for a, b in zip(lo, hi)) ** 0.5 if lo[0] is not None else 0.0
    while True:
        pairs = timebins.candidates(pending, index).where((F.col("q_traj_id") != F.col("traj_id")) & geometry.hints(dist))
        near = geometry.min_distance(pairs).where(F.col("d_min") <= dist)
        best = near.groupBy(F.col("q_traj_id").alias("q_traj"), "traj_id").agg(F.min(F.struct("d_min", "t_min")).alias("b")).select("q_traj", "traj_id", "b.*")
        best = materialize(best.withColumn("rank", F.row_number().over(Window.partitionBy("q_traj").orderBy("d_min", "traj_id"))).where(F.col("rank") <= k))
        full = best.where(F.col("rank") == k).select("q_traj")
        done.append(best if dist > limit else best.join(full, "q_traj", "left_semi"))
        if dist > limit:
            break
        pending = materialize(pending.join(full.withColumnRenamed("q_traj", "traj_id"), "traj_id", "left_anti"))
        if pending.isEmpty():
            break
        dist = max(2 * dist, limit / 1024)
    out = done[0]
    for f in done[1:]:
        out = out.unionByName(f)
    return out


def splice_search(q: DataFrame, d: DataFrame, dist: float, parts: int, r: int = 1) -> DataFrame:
    """TREE over entries cut into parts (less than one segment for each box); contacts are merged again."""
    cut = geometry.splice(d, parts).withColumn("seg_id", F.col("seg_id") * parts + F.col("part")).drop("part")
    return contacts(packed_tree.search(q, packed_tree.build(cut, r), dist))


def snapshot(d: DataFrame, t: float, cell: float) -> DataFrame:
    """Where everything is at time t, counted on an x-y grid."""
    here = d.where((F.col("t0") <= t) & (F.col("t1") > t))
    at = lambda c: F.col(f"{c}0") + (F.col(f"{c}1") - F.col(f"{c}0")) / (F.col("t1") - F.col("t0")) * (F.lit(float(t)) - F.col("t0"))
    return here.groupBy(F.floor(at("x") / cell).alias("cx"), F.floor(at("y") / cell).alias("cy")).agg(F.count(F.lit(1)).alias("n"))


def partitioned(q: DataFrame, path: str, width: float, dist: float, exclude_self: bool = True) -> DataFrame:
    """A search over entries that ``save_by_time`` wrote: queries meet the folders that their time reaches, and no other is read.

    Folders are of start times, so a query also looks back by the longest entry's duration.  The folders' numbers, as
    many at most as there are between the first and the last, pass through the driver."""
    d, known = load_by_time(q.sparkSession, path)
    if known is None or known.longest is None:
        known = Row(longest=0.0, first=0, last=-1)
    since = F.greatest(F.floor((F.col("q_t0") - F.lit(known.longest)) / width), F.lit(known.first))
    until = F.least(F.floor(F.col("q_t1") / width), F.lit(known.last))
    rows = as_queries(q).withColumn("coarse", F.explode(F.when(since <= until, F.sequence(since, until, F.lit(1).cast("long")))))
    reached = [r.coarse for r in rows.select("coarse").distinct().collect()]
    pairs = d.where(F.col("coarse").isin(reached)).join(rows, "coarse")
    return geometry.matches(pairs.where(other_trajectory(exclude_self) & geometry.hints(dist)), dist)
