"""A stored index as a table of edges, by Spark's Python data source API: ``spark.read.format("facet_index").load(path)``."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.dataset as ds
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGES = "shard int, level int, src long, pos int, dst long, dist double"
EDGES_ARROW = pa.schema([("shard", pa.int32()), ("level", pa.int32()), ("src", pa.int64()), ("pos", pa.int32()), ("dst", pa.int64()), ("dist", pa.float64())])


class FilePart(InputPartition):
    def __init__(self, file: str):
        self.file = file


class EdgeReader(DataSourceReader):
    """One partition for each file of the index; ``level`` keeps one level's edges."""

    def __init__(self, path: str, level: str | None):
        self.path, self.level = path, level

    def partitions(self) -> list[InputPartition]:
        return [FilePart(f) for f in sorted(ds.dataset(self.path, format="parquet", partitioning="hive").files)]

    def read(self, partition: FilePart) -> Iterator[pa.RecordBatch]:
        shard = int(partition.file.split("shard=")[1].split("/")[0])
        for batch in ds.dataset(partition.file, format="parquet").to_batches(columns=["id", "lists"], batch_size=1024):
            rows: list[tuple] = []
            for src, lists in zip(batch.column("id").to_pylist(), batch.column("lists").to_pylist()):
                for level, near in enumerate(lists or []):
                    if self.level is None or level == int(self.level):
                        rows += [(shard, level, src, pos, x["dst"], x["dist"]) for pos, x in enumerate(near)]
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), EDGES_ARROW)] if rows else [pa.array([], f.type) for f in EDGES_ARROW], schema=EDGES_ARROW)


class IndexSource(DataSource):
    """Reads what ``index.save`` wrote, from a folder that driver and executors reach by the same path."""

    @classmethod
    def name(cls) -> str:
        return "facet_index"

    def schema(self) -> str:
        return EDGES

    def reader(self, schema) -> EdgeReader:
        path = self.options.get("path")
        if not path:
            raise ValueError("facet_index needs a path")
        return EdgeReader(path.removeprefix("file://").removeprefix("file:"), self.options.get("level"))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(IndexSource)
