"""What all indexes need: extents, dense ids, and rows prefixed for pairs.

Rules that every search follows.  Queries and entries are read as SEGMENT's columns only: what else a table
holds, whatever its name, does not take part and is not in the answer.  A row is a segment by itself: a
segment that is there twice, as a query or as an entry, is answered twice, as by comparing all pairs.
"""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.geometry import AXES
from ..session import materialize
from ..sources.tables import COLUMNS

#: Rows up to which a directory is broadcast; a larger one meets queries by a shuffle.
BROADCAST_ROWS = 500_000


class Extents(NamedTuple):
    n: int
    t_min: float
    t_max: float
    lo: tuple[float, float, float]
    hi: tuple[float, float, float]
    largest: tuple[float, float, float]  # spatial extent of the largest segment, by axis
    longest: float  # duration of the longest segment
    mean: tuple[float, float, float, float] = (0.0, 0.0, 0.0, 0.0)  # extent of the mean segment, by axis, and its duration


def extents(d: DataFrame) -> Extents:
    """One aggregate over all segments; one row comes to the driver.  Without rows, all zero."""
    aggs = [F.count(F.lit(1)), F.min("t0"), F.max("t1"), F.max(F.col("t1") - F.col("t0"))]
    for c in AXES:
        aggs += [F.min(F.least(f"{c}0", f"{c}1")), F.max(F.greatest(f"{c}0", f"{c}1")), F.max(F.abs(F.col(f"{c}1") - F.col(f"{c}0")))]
    means = [*(F.avg(F.abs(F.col(f"{c}1") - F.col(f"{c}0"))) for c in AXES), F.avg(F.col("t1") - F.col("t0"))]
    got = [x or 0.0 for x in d.agg(*aggs, *means).first()]
    r, mean = got[:-4], got[-4:]
    return Extents(int(r[0]), r[1], r[2], tuple(r[4::3]), tuple(r[5::3]), tuple(r[6::3]), r[3], tuple(mean))


def dense_ids(df: DataFrame, order: list[str], name: str = "eid") -> DataFrame:
    """Numbers 0.. in the order given, without a window over all rows.

    Rows are split by range and sorted in each part; the parts' sizes, one number each, give the parts'
    offsets.  The sorted rows are materialized first, so both passes see the same parts.
    """
    spark = df.sparkSession
    ordered = materialize(df.repartitionByRange(*order).sortWithinPartitions(*order))
    placed = ordered.withColumn("_part", F.spark_partition_id()).withColumn("_row", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1))
    sizes = {r["_part"]: r["n"] for r in placed.groupBy("_part").agg(F.count(F.lit(1)).alias("n")).collect()}
    begin, offsets = 0, []
    for part in sorted(sizes):
        offsets.append((part, begin))
        begin += sizes[part]
    if not offsets:
        return df.withColumn(name, F.lit(0).cast("long"))
    table = spark.createDataFrame(offsets, "_part int, _begin long")
    return placed.join(F.broadcast(table), "_part").withColumn(name, F.col("_begin") + F.col("_row")).drop("_part", "_row", "_begin")


def running(values: DataFrame, points: DataFrame, keys: list[str], weight: Column | None = None) -> DataFrame:
    """For each point (keys and _v) the weight of all values (keys and _v) before it, and with those at it: below, upto.

    Order is by keys, then _v.  Equal values are one row; the rows are split by range and summed in each part, and the
    parts' sums, one number each, give where a part begins: a common value or key lands in no task alone."""
    order = [*keys, "_v"]
    a = values.groupBy(*order).agg(F.sum(F.lit(1).cast("long") if weight is None else weight).alias("_n"), F.max(F.lit(0)).alias("_point"))
    b = points.groupBy(*order).agg(F.sum(F.lit(0).cast("long")).alias("_n"), F.max(F.lit(1)).alias("_point"))
    rows = a.unionByName(b).groupBy(*order).agg(F.sum("_n").alias("_n"), F.max("_point").alias("_point"))
    rows = materialize(rows.repartitionByRange(*order).sortWithinPartitions(*order)).withColumn("_part", F.spark_partition_id())
    begin, offsets = 0, []
    for r in sorted(rows.groupBy("_part").agg(F.sum("_n").alias("n")).collect()):
        offsets.append((r._part, begin))
        begin += r.n
    table = values.sparkSession.createDataFrame(offsets, "_part int, _begin long")
    upto = F.sum("_n").over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    summed = rows.withColumn("_upto", upto).join(F.broadcast(table), "_part").where("_point = 1")
    return summed.select(*order, (F.col("_begin") + F.col("_upto") - F.col("_n")).alias("below"), (F.col("_begin") + F.col("_upto")).alias("upto"))


def overlapping(q: DataFrame, d: DataFrame, keys: tuple[str, ...] = (), weight: Column | None = None) -> DataFrame:
    """Queries (q_t0, q_t1 and what else they have) with n, how many entries overlap them in time, or their weight: of
    those with the same keys.  What begins before the query's end, less what ends by its start; no pair is made."""
    k = list(keys)
    begun = running(d.select(*k, F.col("t0").alias("_v"), *([] if weight is None else [weight.alias("_w")])), q.select(*k, F.col("q_t1").alias("_v")), k, None if weight is None else F.col("_w"))
    ended = running(d.select(*k, F.col("t1").alias("_v"), *([] if weight is None else [weight.alias("_w")])), q.select(*k, F.col("q_t0").alias("_v")), k, None if weight is None else F.col("_w"))
    out = q.join(begun.select(*k, F.col("_v").alias("q_t1"), F.col("below").alias("_begun")), [*k, "q_t1"]).join(ended.select(*k, F.col("_v").alias("q_t0"), F.col("upto").alias("_ended")), [*k, "q_t0"])
    return out.select(*q.columns, (F.col("_begun") - F.col("_ended")).alias("n"))


ENTRY_ORDER = ["t0", "traj_id", "seg_id"]


def entries_of(d: DataFrame) -> DataFrame:
    return d.select(*COLUMNS)


def as_queries(q: DataFrame, dist: float | str = 0.0) -> DataFrame:
    """SEGMENT's columns with the prefix q_, and the column of the distance where that is one."""
    return q.select(*(F.col(c).alias(f"q_{c}") for c in COLUMNS + ([dist] if isinstance(dist, str) else [])))


def small(table: DataFrame, rows: int) -> DataFrame:
    """Broadcast if its bound allows."""
    return F.broadcast(table) if rows <= BROADCAST_ROWS else table


def at_distances(q: DataFrame, dists: tuple[float, ...], name: str = "dist") -> DataFrame:
    """Each query once for each distance, in a column that searches take as their distance."""
    return q.select(*COLUMNS, F.explode(F.array(*(F.lit(float(x)) for x in dists))).alias(name))


def other_trajectory(exclude_self: bool) -> Column:
    return F.col("q_traj_id") != F.col("traj_id") if exclude_self else F.lit(True)


def by_trajectory(q: DataFrame, tasks: int | None = None) -> DataFrame:
    """Queries dealt by trajectory and in order inside, so that a task holds neighbours in space."""
    dealt = q.repartition(tasks, "traj_id") if tasks else q.repartition("traj_id")
    return dealt.sortWithinPartitions("traj_id", "seg_id")


def by_start(q: DataFrame) -> DataFrame:
    """Queries in the order of their starts, in ranges."""
    return q.repartitionByRange("t0").sortWithinPartitions(*ENTRY_ORDER)
