"""The session's shared folder and cuts of lineage."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: list[str] = []


def shared_base(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, on this machine alone (as in tests), a folder of our own."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
        if not _own:
            _own.append(tempfile.mkdtemp(prefix="trajdist-"))
            atexit.register(lambda: shutil.rmtree(_own[0], ignore_errors=True))
        base = f"file://{_own[0]}"
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(base)
    return base


def shared_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_base(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame) -> DataFrame:
    """Cuts the lineage in shared storage; partitions and their order stay."""
    shared_base(df.sparkSession)
    return df.checkpoint(eager=True)


def kept(df: DataFrame) -> DataFrame:
    """Written to shared storage as a table and read from there: for rows that are read often, and by column."""
    path = shared_folder(df.sparkSession, "kept")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
