"""Reading the given tables, and persisting indexes as clustered tables."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

SEGMENT = T.StructType(
    [T.StructField("traj_id", T.LongType()), T.StructField("seg_id", T.LongType())]
    + [T.StructField(f"{c}{i}", T.DoubleType()) for i in (0, 1) for c in "txyz"]
)
BY_TIME = T.StructType([*SEGMENT, T.StructField("coarse", T.LongType())])
COLUMNS = [f.name for f in SEGMENT]
MATCH = ["q_traj", "q_seg", "traj_id", "seg_id", "lo", "hi"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def segments_from(df: DataFrame) -> DataFrame:
    """The SEGMENT columns; rows with a null coordinate, or that last no time, are dropped."""
    return df.select(*(F.col(f.name).cast(f.dataType) for f in SEGMENT)).dropna().where("t1 > t0")


def save_index(df: DataFrame, name: str, key: str | list[str], buckets: int, meta: dict, order: tuple[str, ...] = ()) -> None:
    """A managed table bucketed by the key, or keys, that searches join on, sorted inside, with its parameters."""
    text, keys = json.dumps(meta), [key] if isinstance(key, str) else key
    df.withColumn("_meta", F.lit(text)).write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys, *order).saveAsTable(name)


def load_index(spark: SparkSession, name: str) -> tuple[DataFrame, dict]:
    df = spark.table(name)
    first = df.select("_meta").first()
    return df.drop("_meta"), json.loads(first[0]) if first else {}


def save_by_time(df: DataFrame, path: str, width: float) -> None:
    """Parquet folders by coarse time, each sorted by start, so that time predicates prune files and row groups.

    Beside them, in a folder of its own, one row tells the longest duration and the first and last coarse time."""
    df.select(*COLUMNS).withColumn("coarse", F.floor(F.col("t0") / width)).repartition("coarse").sortWithinPartitions("t0").write.mode("overwrite").partitionBy("coarse").parquet(path)
    written = df.sparkSession.read.schema(BY_TIME).parquet(path)
    written.agg(F.max(F.col("t1") - F.col("t0")).alias("longest"), F.min("coarse").alias("first"), F.max("coarse").alias("last")).coalesce(1).write.mode("overwrite").parquet(_reach(path))


def _reach(path: str) -> str:
    return f"{path.rstrip('/')}-reach"


def load_by_time(spark: SparkSession, path: str) -> tuple[DataFrame, Row]:
    """What ``save_by_time`` wrote: the entries with their coarse time, and longest, first and last."""
    return spark.read.schema(BY_TIME).parquet(path), spark.read.parquet(_reach(path)).first()
