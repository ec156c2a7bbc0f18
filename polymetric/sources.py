"""A saved index as a data source: ``spark.read.format("polymetric").load(path)``.

Each Parquet file of a leaf is a partition of the scan. Option ``leaves`` (ids with commas) leaves the other leaves' files
unread; option ``pushdown`` true takes them from the plan's filters and needs ``spark.sql.python.filterPushdown.enabled``. The path must be visible to all executors. The plain Parquet
reader prunes the same way and stays in the JVM; this one serves readers that know only a format's name.
"""

from __future__ import annotations

import os
from collections.abc import Iterator
from glob import glob

from pyspark.sql import SparkSession
from pyspark.sql.types import IntegerType
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition


class LeafFile(InputPartition):
    def __init__(self, path: str, leaf: int):
        self.path, self.leaf = path, leaf


class IndexSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "polymetric"

    def schema(self) -> str:
        import pyarrow.parquet as pq
        from pyspark.sql.pandas.types import from_arrow_schema

        files = _files(self.options["path"])
        if not files:
            return "leaf_id int"
        return from_arrow_schema(pq.read_schema(files[0])).add("leaf_id", IntegerType())

    def reader(self, schema) -> DataSourceReader:  # noqa: ANN001
        kind = PushingReader if self.options.get("pushdown", "false").lower() == "true" else IndexReader
        return kind(self.options["path"], schema, self.options.get("leaves"))


def _files(path: str) -> list[str]:
    return sorted(glob(os.path.join(path.removeprefix("file:"), "objects", "leaf_id=*", "*.parquet")))


class IndexReader(DataSourceReader):
    def __init__(self, path: str, schema, leaves: str | None = None):  # noqa: ANN001
        self.path, self.names = path, [f.name for f in schema.fields]
        self.leaves = None if leaves is None else {int(x) for x in leaves.split(",") if x}

    def partitions(self) -> list[LeafFile]:
        each = [LeafFile(p, int(p.split("leaf_id=")[1].split("/")[0])) for p in _files(self.path)]
        return [p for p in each if self.leaves is None or p.leaf in self.leaves]

    def read(self, partition: LeafFile) -> Iterator:
        import pyarrow as pa
        import pyarrow.parquet as pq

        with pq.ParquetFile(partition.path) as f:
            for batch in f.iter_batches(columns=[n for n in self.names if n != "leaf_id"]):
                yield batch.append_column("leaf_id", pa.array([partition.leaf] * len(batch), pa.int32()))


class PushingReader(IndexReader):
    """Also takes filters on leaf_id from the plan; Spark refuses it while the setting is off."""

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802
        for f in filters:
            wanted = {f.value} if isinstance(f, EqualTo) and f.attribute == ("leaf_id",) else set(f.value) if isinstance(f, In) and f.attribute == ("leaf_id",) else None
            if wanted is None:
                yield f
            else:
                self.leaves = wanted if self.leaves is None else self.leaves & wanted


def register(spark: SparkSession) -> None:
    spark.dataSource.register(IndexSource)
