"""TBIN: entries in bins of their start time.

Every entry is in one bin.  A bin reaches from its start to the latest end of its entries, so a query
looks into each bin that its own time overlaps, and the range condition becomes an equi-join.  A bin of
many entries is dealt over blocks, as many as the directory's count asks for: queries that meet the bin
meet each of its blocks, so no task holds a hot bin alone.
"""

from __future__ import annotations

import math
import uuid
from typing import NamedTuple

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import geometry
from . import tally
from .index import ENTRY_ORDER, Extents, as_queries, dense_ids, entries_of, extents, other_trajectory, small
from .meeting import OWNED, Grid, farthest, fine, spread

#: Most bins of an index: its directory passes through the driver.
MAX_BINS = 1_000_000
#: Entries of a bin beyond which it is dealt over blocks.
BLOCK = 1_000_000


class Bins(NamedTuple):
    m: int
    t_min: float
    width: float

    @classmethod
    def of(cls, ext: Extents, m: int) -> "Bins":
        if not 1 <= m <= MAX_BINS:
            raise ValueError(f"{m} bins: from 1 to {MAX_BINS}")
        return cls(m, ext.t_min, (ext.t_max - ext.t_min) / m)

    def number(self, t: str) -> Column:
        """The bin of a time; what starts at the very end belongs to the last one."""
        if self.width <= 0:
            return F.lit(0)
        return F.least(F.lit(self.m - 1), F.greatest(F.lit(0), F.floor((F.col(t) - F.lit(self.t_min)) / F.lit(self.width)).cast("int")))

    def start(self, b: Column) -> Column:
        return F.lit(self.t_min) + b * F.lit(self.width)


def assign(d: DataFrame, bins: Bins) -> DataFrame:
    return d.withColumn("bin", bins.number("t0"))


def directory(binned: DataFrame, bins: Bins) -> DataFrame:
    """One row per bin that has entries: bounds, id range, count, and the running latest end.

    ``reach_lo`` and ``reach_hi`` are the entries' true bounds.  The table has at most m rows; it is put in order
    on the driver for the running maximum."""
    ids = [F.min("eid").alias("first"), F.max("eid").alias("last")] if "eid" in binned.columns else [F.lit(None).cast("long").alias("first"), F.lit(None).cast("long").alias("last")]
    rows = binned.groupBy("bin").agg(*ids, F.count(F.lit(1)).alias("n"), F.min("t0").alias("reach_lo"), F.max("t1").alias("reach_hi"))
    rows = rows.withColumn("bin_start", bins.start(F.col("bin"))).withColumn("bin_end", F.greatest(bins.start(F.col("bin") + 1), "reach_hi"))
    columns = ["bin", "bin_start", "bin_end", "first", "last", "n", "reach_lo", "reach_hi"]
    got, latest, out = sorted(rows.select(*columns).collect()), -math.inf, []
    for r in got:
        latest = max(latest, r.bin_end)
        out.append((*r, latest))
    schema = "bin int, bin_start double, bin_end double, first long, last long, n long, reach_lo double, reach_hi double, end_cummax double"
    return binned.sparkSession.createDataFrame(out, schema)


def _reach(tight: bool) -> tuple[Column, Column]:
    return (F.col("reach_lo") if tight else F.least("bin_start", "reach_lo")), F.col("reach_hi" if tight else "bin_end")


def bounds(dirs: DataFrame, tight: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Numbers, lower and upper bounds and counts of a directory's bins."""
    lo, hi = _reach(tight)
    got = dirs.select("bin", lo.alias("lo"), hi.alias("hi"), "n").collect()
    return tuple(np.array([r[i] for r in got], kind) for i, kind in enumerate((np.int64, float, float, np.int64)))


def counted(q: DataFrame, index: "TimeBinIndex", tight: bool = False) -> DataFrame:
    """Queries (prefixed) with n, how many entries the bins hold that their time overlaps: from the directory's sums, without a row for each bin."""
    _, lo, hi, n = bounds(index.directory, tight)
    none = F.lit(-1)
    return q.withColumn("n", tally.bin_sums(lo, hi, n[None, :])("q_t0", "q_t1", F.lit(0), none, none, none)["w"])


def overlaps(q: DataFrame, dirs: DataFrame, bins: Bins, how: str = "bounded", tight: bool = False, keep: tuple[str, ...] = ("first", "last", "n")) -> DataFrame:
    """Queries (prefixed) with each bin that their time overlaps, and ``keep`` of its row in the directory.

    ``scan`` compares every query with every bin.  ``bounded`` takes the upper bin from the query's end,
    and the lower one from a table that tells, for the bin of the query's start, the first bin whose running
    latest end is beyond; only what lies between is looked at.  With ``tight`` a bin reaches no further than its entries."""
    lo, hi = _reach(tight)
    d = small(dirs.select("bin", lo.alias("_lo"), hi.alias("_hi"), *keep), bins.m)
    meets = (F.col("q_t0") < F.col("_hi")) & (F.col("_lo") < F.col("q_t1"))
    if how == "scan":
        return q.join(d, meets).drop("_lo", "_hi")
    got = sorted(dirs.select("bin", "end_cummax").collect())
    table, k = [], 0
    for b in range(bins.m):
        while k < len(got) and got[k].end_cummax <= bins.t_min + b * bins.width and got[k].bin < b:
            k += 1
        table.append((b, got[k].bin if k < len(got) else b))
    # Most bins begin with themselves: only the others need the table.  One bin lower, as the last bit of a bin's start may lie above its own entries.
    start, table = bins.number("q_t0"), [(b, f) for b, f in table if f < b]
    if table:
        first = small(q.sparkSession.createDataFrame(table, "_b int, _from int"), bins.m)
        q = q.withColumn("_b", start).join(first, "_b", "left").withColumn("_from", F.coalesce("_from", "_b")).drop("_b")
    else:
        q = q.withColumn("_from", start)
    ranged = q.withColumn("bin", F.explode(F.sequence(F.greatest(F.col("_from") - 1, F.lit(0)), bins.number("q_t1")))).drop("_from")
    return ranged.join(d, "bin").where(meets).drop("_lo", "_hi")


class TimeBinIndex(NamedTuple):
    entries: DataFrame  # segments with bin (and eid; and block, where a bin has several)
    directory: DataFrame
    bins: Bins
    block: int = 0  # entries of a block; 0 where every bin is one
    ext: Extents | None = None  # of the entries; without it searches meet in whole bins
    grid: Grid | None = None  # the cells of the entries' h, where they are laid out by them


def block_of(blocks: Column) -> Column:
    return F.pmod(F.xxhash64("traj_id", "seg_id"), blocks).cast("int")


def every_block(rows: DataFrame, n: Column, block: int) -> DataFrame:
    """Query rows once for each block of a list of ``n`` entries."""
    return rows.withColumn("block", F.explode(F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil(n / block).cast("int") - 1)))) if block else rows


def build(d: DataFrame, m: int, ids: bool = False, block: int = BLOCK) -> TimeBinIndex:
    ext = extents(d)
    bins = Bins.of(ext, m)
    entries = assign(dense_ids(entries_of(d), ENTRY_ORDER) if ids else entries_of(d), bins)
    dirs = directory(entries, bins)
    hot = dirs.where(F.col("n") > block).select("bin", F.ceil(F.col("n") / block).cast("int").alias("_blocks"))
    if hot.isEmpty():
        return TimeBinIndex(entries, dirs, bins, ext=ext)
    dealt = entries.join(small(hot, m), "bin", "left").withColumn("block", block_of(F.coalesce("_blocks", F.lit(1)))).drop("_blocks")
    return TimeBinIndex(dealt, dirs, bins, block, ext)


def in_place(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Stored as a table that is bucketed by the keys of its join, a file for each bucket: searches then move queries only.

    The table is in the session's warehouse, under a name of its own; ``forget`` drops it."""
    spark = rows.sparkSession
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    name = f"trajdist_{uuid.uuid4().hex}"
    rows.repartition(buckets, *keys).write.bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)
    return spark.table(name)


def forget(rows: DataFrame) -> None:
    """Drops the table that ``in_place`` made."""
    for f in {f.rsplit("/", 2)[-2] for f in rows.inputFiles()}:
        if f.startswith("trajdist_"):
            rows.sparkSession.sql(f"DROP TABLE IF EXISTS {f}")


def meet(queries: DataFrame, entries: DataFrame, keys: list[str]) -> DataFrame:
    """Queries with the entries of their lists, by a merge of sorted sides: entries are never broadcast, and those that are laid
    out stay where they are.  What comes after the merge is a stage of its own, small enough to be compiled."""
    return queries.hint("merge").join(entries, keys)


def keys_of(index: TimeBinIndex) -> list[str]:
    return ["bin", "block"] if index.block else ["bin"]


def store(index: TimeBinIndex) -> TimeBinIndex:
    """The index with its entries laid out for searches, which meet them in whole bins."""
    return index._replace(entries=in_place(index.entries, keys_of(index)), ext=None)


def schedule(q: DataFrame, index: TimeBinIndex) -> DataFrame:
    """For each query the range of entry ids from its first to its last overlapped bin; needs ids in the index."""
    mine = overlaps(as_queries(q), index.directory, index.bins)
    return mine.groupBy("q_traj_id", "q_seg_id").agg(F.min("first").alias("entry_min"), F.max("last").alias("entry_max")).select(
        F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg"), "entry_min", "entry_max", (F.col("entry_max") - F.col("entry_min") + 1).alias("n_candidates")
    )


def candidates(q: DataFrame, index: TimeBinIndex, mode: str = "bins", how: str = "bounded", tight: bool = False, block: int = 256, dist: float | str = 0.0) -> DataFrame:
    """Pairs before the time test.  ``bins`` joins the overlapped bins only; ``range`` all ids of the schedule's range, by blocks of ids."""
    qs = as_queries(q, dist)
    if mode == "range":
        # Equal segments have equal ranges, so they are one row here and are repeated again.
        met = overlaps(qs.groupBy(*qs.columns).agg(F.count(F.lit(1)).alias("_times")), index.directory, index.bins)
        rows = met.groupBy(*qs.columns, "_times").agg(F.min("first").alias("entry_min"), F.max("last").alias("entry_max"))
        rows = rows.withColumn("_k", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_times")))).drop("_times")
        rows = rows.withColumn("_k", F.explode(F.sequence(F.expr(f"entry_min div {block}"), F.expr(f"entry_max div {block}"))))
        return rows.join(index.entries.withColumn("_k", F.expr(f"eid div {block}")), "_k").where(F.col("eid").between(F.col("entry_min"), F.col("entry_max"))).drop("_k", "entry_min", "entry_max")
    met = every_block(overlaps(qs, index.directory, index.bins, how, tight, keep=("n",)), F.col("n"), index.block)
    return meet(met.drop("n"), index.entries, keys_of(index))


def placed(index: TimeBinIndex, dist: float) -> TimeBinIndex:
    """The index with its bins dealt over cells as wide as a query of that distance reaches: entries with cell h and low."""
    grid = fine(index.ext, dist)
    return index._replace(entries=spread(index.entries, grid).drop("_at"), grid=grid)


def near(q: DataFrame, index: TimeBinIndex, dist: float | str, how: str = "bounded", tight: bool = False) -> DataFrame:
    """Pairs that may be within the distance: of the overlapped bins, those that share a cell, each once."""
    if index.grid is None and index.ext is not None:
        index = placed(index, farthest(q, dist))
    if index.grid is None or max(index.grid.n) == 1:
        pairs = candidates(q, index, how=how, tight=tight, dist=dist)
        return pairs.drop("h", "low")
    met = every_block(overlaps(as_queries(q, dist), index.directory, index.bins, how, tight, keep=("n",)), F.col("n"), index.block).drop("n")
    return meet(spread(met, index.grid, dist, "q_").drop("_at"), index.entries, [*keys_of(index), "h"]).where(OWNED).drop("h", "q_low", "low")


def search(q: DataFrame, index: TimeBinIndex, dist: float | str, mode: str = "bins", how: str = "bounded", tight: bool = False, exclude_self: bool = True) -> DataFrame:
    pairs = near(q, index, dist, how, tight) if mode == "bins" else candidates(q, index, mode, how, tight, dist=dist)
    return geometry.matches(pairs.where(other_trajectory(exclude_self) & geometry.hints(dist)), dist)


def build_classes(d: DataFrame, m: int) -> DataFrame:
    """Entries with a length class beside the bin, so that one long entry does not stretch a bin of short ones.

    Class c holds entries of duration up to 2^c bin widths; its bins are that wide."""
    bins = Bins.of(extents(d), m)
    width = bins.width or 1.0
    cls = F.greatest(F.lit(0), F.ceil(F.log2((F.col("t1") - F.col("t0")) / F.lit(width)))).cast("int")
    out = entries_of(d).withColumn("cls", cls)
    return out.withColumn("bin", F.floor((F.col("t0") - F.lit(bins.t_min)) / (F.lit(width) * F.pow(F.lit(2.0), F.col("cls")))).cast("long")).withColumn("_width", F.lit(width)).withColumn("_t_min", F.lit(bins.t_min))


def search_classes(q: DataFrame, classed: DataFrame, dist: float | str, exclude_self: bool = True) -> DataFrame:
    """A query meets, in each class, the bins of its own time and the one before: no entry reaches further."""
    r = classed.agg(F.max("_width"), F.max("_t_min"), F.collect_set("cls")).first()
    width, t_min, classes = (1.0, 0.0, [0]) if r[0] is None else r
    qs = as_queries(q, dist).withColumn("cls", F.explode(F.array(*(F.lit(c) for c in sorted(classes)))))
    at = lambda c: F.floor((F.col(c) - F.lit(t_min)) / (F.lit(width) * F.pow(F.lit(2.0), F.col("cls")))).cast("long")
    qs = qs.withColumn("bin", F.explode(F.sequence(at("q_t0") - 1, at("q_t1"))))
    pairs = qs.join(classed.drop("_width", "_t_min"), ["cls", "bin"])
    return geometry.matches(pairs.where(other_trajectory(exclude_self) & geometry.hints(dist)), dist)
