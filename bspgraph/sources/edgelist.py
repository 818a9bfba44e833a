"""An edge-list format for ``spark.read.format("edgelist")``.

The file is cut into byte ranges, one per partition, at line ends.  It is for
paths that every worker sees as a file; other stores go by ``read_edge_list``.
"""

from __future__ import annotations

import os

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..shipping import ship


class _Range(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class _Reader(DataSourceReader):
    def __init__(self, path: str, partitions: int):
        self._path, self._parts = path, partitions

    def partitions(self):
        size = os.path.getsize(self._path)
        step = max(1, -(-size // self._parts))
        return [_Range(a, min(size, a + step)) for a in range(0, size, step)]

    def read(self, partition):
        with open(self._path, "rb") as file:
            if partition.start:
                file.seek(partition.start - 1)
                file.readline()  # a line belongs to the range its first byte is in
            while file.tell() < partition.end:
                parts = file.readline().split()
                if len(parts) >= 2 and not parts[0].startswith(b"#"):
                    yield int(parts[0]), int(parts[1])


class EdgeListSource(DataSource):
    @classmethod
    def name(cls):
        return "edgelist"

    def schema(self):
        return "src long, dst long"

    def reader(self, schema):
        return _Reader(self.options["path"], int(self.options.get("partitions", 8)))


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.dataSource.register(EdgeListSource)
