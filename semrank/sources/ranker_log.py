"""Logs of a ranking service as a Spark data source: JSON lines, one object per call, files as partitions."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

FORMAT = "semrank_log"
SCHEMA = "call_id string, query string, ids array<bigint>, ranked array<bigint>, seconds double"


class _File(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


class _LogReader(DataSourceReader):
    def __init__(self, path: str, names: list[str]):
        self.path, self.names = path, names

    def _system(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.path if "://" in self.path else f"file://{self.path}")

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        where, root = self._system()
        return [_File(x.path) for x in sorted(where.get_file_info(fs.FileSelector(root)), key=lambda x: x.path) if x.base_name.endswith(".jsonl")] or [_File("")]

    def read(self, partition: _File) -> Iterator[tuple]:
        """A line that isn't an object is skipped: services cut lines off when they are stopped."""
        if not partition.path:
            return
        where, _ = self._system()
        with where.open_input_stream(partition.path) as f:
            for line in f.read().decode("utf-8", "replace").splitlines():
                try:
                    row = json.loads(line)
                except ValueError:
                    continue
                if isinstance(row, dict):
                    yield tuple(row.get(n) for n in self.names)


class RankerLogSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return FORMAT

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> DataSourceReader:
        return _LogReader(self.options["path"], schema.names)


def read_logs(spark: SparkSession, path: str) -> DataFrame:
    spark.dataSource.register(RankerLogSource)
    return spark.read.format(FORMAT).option("path", path).load()
