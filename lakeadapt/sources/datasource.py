"""A Python data source that opens a directory of small Parquet tables as columns: `format("lake")`.

`path` is a directory on a file system that every machine mounts; tables are packed `tables_per_task` to a partition. As a
stream, a table is read once, when its file first appears.
"""

from __future__ import annotations

import glob
import os
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

SCHEMA = "column_id string, table_id string, position int, n_rows long, n_null long, cells array<string>"


class _Tables(InputPartition):
    def __init__(self, paths: list[str]):
        self.paths = paths


def _columns(path: str, max_cells: int) -> Iterator[tuple]:

    import pyarrow.parquet as pq

    table = pq.read_table(path)
    name = os.path.splitext(os.path.basename(path))[0]
    for k, column in enumerate(table.columns):
        texts = [str(v) for v in column.slice(0, max_cells).to_pylist() if v is not None]
        yield (f"{name}#{k}", name, k, table.num_rows, column.null_count, texts)


def _files(path: str) -> list[str]:
    return sorted(glob.glob(os.path.join(path, "*.parquet")))


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"].removeprefix("file://")
        self.pack, self.cells = int(options.get("tables_per_task", 64)), int(options.get("max_cells", 16))

    def partitions(self) -> list[_Tables]:
        files = _files(self.path)
        return [_Tables(files[k : k + self.pack]) for k in range(0, len(files), self.pack)] or [_Tables([])]

    def read(self, partition: _Tables) -> Iterator[tuple]:
        for path in partition.paths:
            yield from _columns(path, self.cells)


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, options: dict):
        self.path, self.cells = options["path"].removeprefix("file://"), int(options.get("max_cells", 16))

    def initialOffset(self) -> dict:
        return {"last": ""}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        new = [f for f in _files(self.path) if f > start["last"]]
        return iter([r for f in new for r in _columns(f, self.cells)]), {"last": new[-1] if new else start["last"]}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return iter([r for f in _files(self.path) if start["last"] < f <= end["last"] for r in _columns(f, self.cells)])


class LakeSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "lake"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _Stream(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(LakeSource)
