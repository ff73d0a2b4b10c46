"""A Python data source for edge lists in text files: ``spark.read.format("edge_list").load(path)``."""

from __future__ import annotations

import glob
import os

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, path: str, low: int, high: int):
        self.path, self.low, self.high = path, low, high


class EdgeListReader(DataSourceReader):
    """Reads byte ranges of the files; a line belongs to the range that its first byte is in."""

    def __init__(self, options):
        self.path, self.size = options["path"], int(options.get("bytes", 32 << 20))

    def partitions(self):
        files = sorted(glob.glob(f"{self.path}/*")) if os.path.isdir(self.path) else sorted(glob.glob(self.path))
        return [_Range(f, low, low + self.size) for f in files for low in range(0, max(1, os.path.getsize(f)), self.size)]

    def read(self, partition):
        with open(partition.path, "rb") as f:
            f.seek(max(0, partition.low - 1))
            if partition.low:
                f.readline()
            while f.tell() < partition.high and (line := f.readline()):
                parts = line.replace(b",", b" ").split()
                if len(parts) >= 2 and not line.startswith(b"#"):
                    u, v = int(parts[0]), int(parts[1])
                    if u != v:
                        yield min(u, v), max(u, v)


class EdgeListSource(DataSource):
    @classmethod
    def name(cls):
        return "edge_list"

    def schema(self):
        return "u long, v long"

    def reader(self, schema):
        return EdgeListReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(EdgeListSource)
