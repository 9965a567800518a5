"""The coordinate matrix format as a data source: spark.read.format("matrix_coo").load(path).

Partitions are byte ranges of a file that the executors can open; for files that only Spark's readers reach take
sources.edges.read_matrix_coordinates."""

from __future__ import annotations

import os
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Range(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class MatrixReader(DataSourceReader):
    def __init__(self, path: str, size: int):
        self.path, self.size = path, size

    def partitions(self) -> list[Range]:
        total, begin = os.path.getsize(self.path), 0
        with open(self.path, "rb") as f:  # entries begin after the line of sizes
            for line in f:
                begin += len(line)
                if line.strip() and not line.startswith(b"%"):
                    break
        return [Range(a, min(a + self.size, total)) for a in range(begin, total, self.size)]

    def read(self, partition: Range) -> Iterator[tuple[int, int]]:
        """Lines that begin in the range."""
        with open(self.path, "rb") as f:
            f.seek(partition.start - 1)
            if f.read(1) != b"\n":
                f.readline()
            while f.tell() < partition.end and (line := f.readline()):
                parts = line.split()
                if len(parts) >= 2:
                    yield int(parts[0]) - 1, int(parts[1]) - 1


class MatrixSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "matrix_coo"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> MatrixReader:
        return MatrixReader(self.options["path"], int(self.options.get("partitionbytes", 64 << 20)))
