"""A Python data source over a stored cell lookup: the ranges of cells asked for are partitions, read by file statistics.

``spark.read.format("cell_lookup").option("path", ...).option("cells", "0-99,500-750").load()``
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "h long, traj_id long, seg_id long"


class CellRange(NamedTuple):
    lo: int
    hi: int


class _Part(InputPartition):
    def __init__(self, cells: CellRange):
        super().__init__(cells)


class CellLookup(DataSource):
    """h, traj_id, seg_id of the cells asked for; all of them where ``cells`` is not given."""

    @classmethod
    def name(cls) -> str:
        return "cell_lookup"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> "CellReader":
        return CellReader(self.options)


class CellReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"]
        asked = options.get("cells") or f"0-{2**62}"
        self.ranges = [CellRange(*map(int, r.split("-"))) for r in asked.split(",")]

    def partitions(self) -> list[InputPartition]:
        return [_Part(r) for r in self.ranges]

    def read(self, partition: InputPartition) -> Iterator:
        import pyarrow.dataset as ds
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(self.path) if "://" in self.path else (fs.LocalFileSystem(), self.path.removeprefix("file:"))
        h = ds.field("h")
        cells = partition.value
        rows = ds.dataset(path, filesystem=store, format="parquet", exclude_invalid_files=False).scanner(columns=["h", "traj_id", "seg_id"], filter=(h >= cells.lo) & (h <= cells.hi))
        yield from (b for b in rows.to_batches() if b.num_rows)


def save_lookup(lookup: DataFrame, path: str) -> None:
    """Sorted by cell in ranges, so that a file's statistics tell whether it holds a cell."""
    lookup.select("h", "traj_id", "seg_id").repartitionByRange("h").sortWithinPartitions("h").write.mode("overwrite").parquet(path)


def read_cells(spark: SparkSession, path: str, ranges: list[tuple[int, int]]) -> DataFrame:
    spark.dataSource.register(CellLookup)
    return spark.read.format("cell_lookup").option("path", path).option("cells", ",".join(f"{a}-{z}" for a, z in ranges)).load()
