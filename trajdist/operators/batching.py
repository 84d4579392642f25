"""Searches in bounded memory: rounds with a buffer for each query, and batches for a result buffer."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import materialize, shared_folder
from .index import dense_ids


def cell_rounds(demand: DataFrame, size: int) -> DataFrame:
    """q_traj, q_seg, demand, round, capacity, chunks of each query.

    In every round the buffer is split evenly among the pending queries; those whose demand fits are done.
    If none fits, the smallest go first, as many as fit together; a query that needs more than the whole
    buffer is served alone, in chunks of it.  What is pending is always the end of the queries' order by demand, so
    a round is one small aggregate over the ordered queries; rounds are at most as many as queries.
    """
    ordered = materialize(running_sum(demand.select("q_traj", "q_seg", "demand"), ["demand", "q_traj", "q_seg"]))
    n, begin, ends = ordered.count(), 0, []
    while begin < n:
        capacity = size // (n - begin)
        done = ordered.where(F.col("demand") <= capacity).count()
        if done <= begin:
            spent = ordered.where(F.col("_i") == begin).first()["_before"]
            fits = (F.col("_before") + F.col("demand") - spent <= size) | (F.col("_i") == begin)
            done, capacity = ordered.where((F.col("_i") >= begin) & fits).count() + begin, size
        ends.append((len(ends) + 1, capacity, begin, done))
        begin = done
    table = demand.sparkSession.createDataFrame(ends, "round int, capacity long, _a long, _z long")
    rows = ordered.join(F.broadcast(table), (F.col("_i") >= F.col("_a")) & (F.col("_i") < F.col("_z")))
    return rows.select("q_traj", "q_seg", "demand", "round", "capacity", F.greatest(F.lit(1).cast("long"), F.ceil(F.col("demand") / size)).alias("chunks"))


def running_sum(demand: DataFrame, order: list[str], part: int = 4096) -> DataFrame:
    """Adds ``_i``, the place in the order, and ``_before``, the demand of all rows before: over parts of the order, then inside them.

    However many rows there are, about 65,536 sums of parts at most come to the driver."""
    rows = dense_ids(demand, order, "_i")
    rows = rows.withColumn("_part", F.expr(f"_i div {max(part, rows.count() >> 16)}"))
    sums, begin, table = sorted(rows.groupBy("_part").agg(F.sum("demand").alias("n")).collect()), 0, []
    for r in sums:
        table.append((r["_part"], begin))
        begin += r["n"]
    offsets = demand.sparkSession.createDataFrame(table, "_part long, _begin long")
    inside = F.coalesce(F.sum("demand").over(Window.partitionBy("_part").orderBy("_i").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.join(F.broadcast(offsets), "_part").withColumn("_before", F.col("_begin") + inside).drop("_part", "_begin")


def by_capacity(demand: DataFrame, capacity: int, order: list[str]) -> DataFrame:
    """Adds ``batch_id``: queries in order, cut where the running sum of demand passes multiples of the capacity."""
    return running_sum(demand, order).withColumn("batch_id", (F.col("_before") / capacity).cast("long")).drop("_i", "_before")


def rounds(batched: DataFrame) -> int:
    """Number of invocations that the batches need."""
    return batched.select("batch_id").distinct().count()


_RESULT = "q_traj long, q_seg long, traj_id long, seg_id long, lo double, hi double"


def run_batches(q: DataFrame, batched: DataFrame, search: Callable[[DataFrame], DataFrame], key: str = "batch_id", chunked: Callable[[DataFrame, int, int], DataFrame] | None = None) -> DataFrame:
    """Runs ``search(queries)`` batch by batch, in the order of ``key``, and returns all results from where they were written.

    Each invocation overwrites a folder of its own, so one that is run again leaves its results once.  Queries whose
    ``chunks`` are more than one are answered by ``chunked(queries, i, chunks)``, pass by pass."""
    spark = q.sparkSession
    out = shared_folder(spark, "batches")
    more = ["chunks"] if chunked else []
    plan = materialize(batched.select(F.col("q_traj").alias("traj_id"), F.col("q_seg").alias("seg_id"), F.col(key).alias("_batch"), *more).distinct())
    keyed = materialize(q.join(plan, ["traj_id", "seg_id"]))
    # One row for each invocation.
    for r in sorted(plan.select("_batch", *more).distinct().collect()):
        mine = keyed.where(F.col("_batch") == r[0])
        if chunked is None or r.chunks == 1:
            search(mine.where("chunks = 1") if chunked else mine).write.mode("overwrite").parquet(f"{out}/b{r[0]}")
        else:
            for i in range(r.chunks):
                chunked(mine.where(F.col("chunks") == r.chunks), i, r.chunks).write.mode("overwrite").parquet(f"{out}/b{r[0]}-{r.chunks}-{i}")
    if plan.isEmpty():
        return spark.createDataFrame([], _RESULT)
    return spark.read.schema(_RESULT).option("recursiveFileLookup", "true").parquet(out)


def demand_class(demand: str = "demand") -> Column:
    """Queries of like demand share a class: the power of two below it, -1 for none."""
    return F.when(F.col(demand) > 0, F.floor(F.log2(demand)).cast("int")).otherwise(-1)


def grouped(demand: DataFrame) -> DataFrame:
    """class, queries, total: queries of like demand stand together, so that a heavy one does not hold up light ones."""
    return demand.groupBy(demand_class().alias("class")).agg(F.count(F.lit(1)).alias("queries"), F.sum("demand").cast("long").alias("total"))
