"""The experiment's trajectories, built from the given tables.

Positions come from integer arithmetic and one last division, so every engine builds the same bits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import COLUMNS, table

#: lineitem has no key: all its columns, ship date first, make an order.
ORDER = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
#: Steps of a trajectory, as in the experiments: a walk is the first so many rows of its key, and longer histories end there.
WALK_STEPS, DENSE_STEPS = 400, 193
DENSITY = 0.112
EVENT_EPOCH = 1704067200000000
#: The height of each event type.
EVENT_Z = {"click": 0, "error": 1, "purchase": 2, "signup": 3, "view": 4}


def join_points(points: DataFrame) -> DataFrame:
    """Segments of consecutive points (traj_id, step, t, x, y, z); those that last no time are dropped."""
    w = Window.partitionBy("traj_id").orderBy("step")
    out = points.select("traj_id", F.col("step").alias("seg_id"), *(F.col(c).alias(f"{c}0") for c in "txyz"), *(F.lead(c).over(w).alias(f"{c}1") for c in "txyz"))
    return out.where("t1 > t0").select(*COLUMNS)


def _steps(spark: SparkSession, sf_dir: str, key: str, columns: dict[str, str], most: int) -> DataFrame:
    """Trajectory, step and running sums of integer columns of lineitem."""
    w = Window.partitionBy("k").orderBy(*ORDER)
    rows = table(spark, sf_dir, "lineitem").withColumn("k", F.col(key))
    sums = {n: F.sum(F.expr(e)).over(w.rowsBetween(Window.unboundedPreceding, 0)) for n, e in columns.items()}
    return rows.select("k", (F.row_number().over(w) - 1).cast("long").alias("step"), *(c.alias(n) for n, c in sums.items())).where(F.col("step") < most)


def seg_walk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sparse random walks with shifted starts."""
    sums = {"sx": "CAST(l_quantity AS BIGINT) - 25", "sy": "CAST(round(100 * l_discount) AS BIGINT) - 5", "sz": "CAST(round(100 * l_tax) AS BIGINT) - 4"}
    steps = _steps(spark, sf_dir, "l_suppkey", sums, WALK_STEPS)
    points = steps.select(
        F.col("k").alias("traj_id"), "step", F.expr("CAST(step + (k * 7919) % 101 AS DOUBLE)").alias("t"),
        *(F.expr(f"CAST(s{c} + (k * {m}) % 101 AS DOUBLE)").alias(c) for c, m in zip("xyz", (37, 53, 71))),
    )
    return join_points(points)


def seg_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Observed positions of users."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    code = F.create_map(*(F.lit(x) for kv in EVENT_Z.items() for x in kv))
    # Microseconds without the session's time zone: a timestamp without zone against the epoch.
    micros = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)")
    points = table(spark, sf_dir, "events").select(
        F.col("user_id").alias("traj_id"), (F.row_number().over(w) - 1).cast("long").alias("step"), ((micros - EVENT_EPOCH) / F.lit(3600000000.0)).alias("t"),
        F.col("value").alias("x"), F.get_json_object("props", "$.k").cast("double").alias("y"), (25 * code[F.col("event_type")]).cast("double").alias("z"),
    )
    return join_points(points)


def dense_side(n: int) -> int:
    """Thousandths of the side of the cube that keeps the density for n trajectories."""
    return round(1000 * (n / DENSITY) ** (1 / 3))


def seg_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Walks kept in a cube by reflection, a fifth of the side beyond its faces."""
    n = table(spark, sf_dir, "lineitem").agg(F.countDistinct("l_partkey")).first()[0]
    side = dense_side(n)
    period, over = 7 * side // 5, side // 5
    sign = lambda e: f"CASE WHEN {e} % 2 = 0 THEN 1000 ELSE -1000 END"
    sums = {
        "sx": f"(1 + CAST(l_quantity AS BIGINT) % 5) * {sign('l_orderkey')}",
        "sy": f"(1 + l_suppkey % 5) * {sign('l_linenumber')}",
        "sz": f"(1 + l_orderkey % 5) * {sign('CAST(round(100 * l_tax) AS BIGINT)')}",
    }
    steps = _steps(spark, sf_dir, "l_partkey", sums, DENSE_STEPS)
    starts = {"x": (7919, 1009), "y": (6271, 1013), "z": (3571, 1019)}
    points = steps.select(
        F.col("k").alias("traj_id"), "step", F.col("step").cast("double").alias("t"),
        *(F.expr(f"({period} - abs(pmod((k * {a}) % {b} * {side} div {b} + s{c} + {over}, {2 * period}) - {period}) - {over}) / 1000.0D").alias(c) for c, (a, b) in starts.items()),
    )
    return join_points(points)


def seg_vector(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings as a trajectory for each label: three components are the place, the id is the time."""
    w = Window.partitionBy("label").orderBy("vec_id")
    points = table(spark, sf_dir, "embeddings").select(
        F.col("label").cast("long").alias("traj_id"), (F.row_number().over(w) - 1).cast("long").alias("step"), F.col("vec_id").cast("double").alias("t"),
        *(F.col("embedding")[i].cast("double").alias(c) for i, c in enumerate("xyz")),
    )
    return join_points(points)


SCENARIOS = {"walk": seg_walk, "event": seg_event, "dense": seg_dense}
#: The distance that the registered searches use.
DISTANCE = {"walk": 20.0, "event": 10.0, "dense": 9.4}
#: Time bins, slabs, cells per axis and segments per leaf of the registered searches.
BINS = {"walk": 1000, "event": 1000, "dense": 48}
SLABS = {"walk": 4, "event": 2, "dense": 2}
CELLS = {"walk": 20, "event": 10, "dense": 10}
LEAF = {"walk": 10, "event": 1, "dense": 4}


def segments(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return SCENARIOS[name](spark, sf_dir)


#: Every how-many-th trajectory is a query: a fixed share, so that queries grow with the table.
QUERIES = {"walk": 10, "event": 5, "dense": 50}


def queries_of(d: DataFrame, name: str) -> DataFrame:
    """The query slice of a scenario: whole trajectories."""
    return d.where(F.col("traj_id") % QUERIES[name] == 0)


def random_walk(spark: SparkSession, trajectories: int, steps: int, seed: int, spread: float = 100.0, step: float = 1.0, keys: DataFrame | None = None) -> DataFrame:
    """Seeded walks of any size, for scale tests: uniform starts in space and time, normal steps.  ``keys``, one column, names the trajectories."""
    w = Window.partitionBy("traj_id").orderBy("step")
    places = spark.range(trajectories * steps).select(F.expr(f"id div {steps}").alias("traj_id"), F.expr(f"id % {steps}").alias("step"))
    if keys is not None:
        places = keys.toDF("traj_id").withColumn("step", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(steps - 1).cast("long"))))
    rows = places.select("*", *(F.randn(seed + i).alias(f"r{c}") for i, c in enumerate("xyz")))
    start = lambda i: F.pmod(F.xxhash64("traj_id", F.lit(seed + i)), F.lit(1_000_003)) / 1_000_003.0 * spread
    points = rows.select("traj_id", "step", (F.col("step") + start(9)).alias("t"), *((start(i) + step * F.sum(f"r{c}").over(w)).alias(c) for i, c in enumerate("xyz")))
    return join_points(points)


def bounded_walk(spark: SparkSession, trajectories: int, steps: int, seed: int, step: float = 0.003, keys: DataFrame | None = None) -> DataFrame:
    """Seeded walks held in a cube of the given density by reflection."""
    side = (trajectories / DENSITY) ** (1 / 3)
    low, period = -0.2 * side, 1.4 * side
    free = random_walk(spark, trajectories, steps, seed, side, step * side, keys)
    fold = lambda c: F.lit(period) - F.abs(F.expr(f"pmod({c} - ({low}), {2 * period})") - period) + low
    return free.select("traj_id", "seg_id", "t0", *(fold(f"{c}0").alias(f"{c}0") for c in "xyz"), "t1", *(fold(f"{c}1").alias(f"{c}1") for c in "xyz"))
