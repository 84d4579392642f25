"""The folder that the driver and all executors share, and small helpers around it."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from urllib.parse import urlparse

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_own: list[str] = []


def _forget() -> None:
    import shutil

    for d in _own:
        shutil.rmtree(d, ignore_errors=True)


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder's URI below spark.checkpoint.dir; where that is unset, on this machine alone, below one of our own."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
        if not _own:
            _own.append(tempfile.mkdtemp(prefix="shared-"))
            atexit.register(_forget)
        base = f"file://{_own[0]}"
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def filesystem(uri: str):
    """The pyarrow file system of a shared folder, and the path in it.  Runs on any executor."""
    from pyarrow import fs

    if urlparse(uri).scheme in ("", "file"):
        return fs.LocalFileSystem(), urlparse(uri).path
    return fs.FileSystem.from_uri(uri)


def write_file(folder: str, name: str, fill) -> str:
    """Writes folder/name through ``fill(stream)``.  A task that runs twice leaves one whole file."""
    store, path = filesystem(folder)
    store.create_dir(path, recursive=True)
    part = f"{path}/.{name}.{uuid.uuid4().hex}"
    with store.open_output_stream(part) as out:
        fill(out)
    store.move(part, f"{path}/{name}")
    return f"{folder}/{name}"


def stored(df: DataFrame, folder: str) -> DataFrame:
    """Writes df as Parquet and reads it again: a cut of lineage that outlives lost executors."""
    df.write.mode("overwrite").parquet(folder)
    return df.sparkSession.read.schema(df.schema).parquet(folder)


def remainder(doc_id: Column, m: int) -> Column:
    """crc32 of the id as text, modulo m; null ids give null."""
    return F.crc32(doc_id.cast("string").cast("binary")) % m


def lean(run):
    """A mapInArrow function that hands freed memory back at each task's end: workers live on through later stages."""

    def wrapped(batches):
        yield from run(batches)
        import ctypes

        import pyarrow as pa

        pa.default_memory_pool().release_unused()
        try:
            ctypes.CDLL(None).malloc_trim(0)
        except (OSError, AttributeError):  # not glibc
            pass

    return wrapped


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
