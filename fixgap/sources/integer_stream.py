"""Encoded tables as files of integers: a line for each row, row number first. Written by Spark, read by a Python data source."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.encoding import to_stream

SCHEMA = "row_no int, ints array<bigint>"


def write(encoded: DataFrame, path: str) -> None:
    to_stream(encoded).select(F.concat_ws(" ", F.col("row_no").cast("string"), F.array_join(F.col("ints").cast("array<string>"), " ")).alias("value")).write.text(path)


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[_File]:
        import pyarrow.fs as pafs

        fs, root = pafs.FileSystem.from_uri(self.path)
        found = fs.get_file_info(pafs.FileSelector(root))
        return [_File(f.path) for f in sorted(found, key=lambda f: f.path) if f.is_file and f.base_name.startswith("part-")]

    def read(self, partition: _File) -> Iterator[tuple]:
        import pyarrow.fs as pafs

        fs, _ = pafs.FileSystem.from_uri(self.path)
        with fs.open_input_stream(partition.path) as f:
            rest = b""
            while chunk := f.read(1 << 20):
                *lines, rest = (rest + chunk).split(b"\n")
                yield from map(self._row, lines)
            if rest:
                yield self._row(rest)

    @staticmethod
    def _row(line: bytes) -> tuple:
        first, *ints = line.split()
        return int(first), [int(x) for x in ints]


class IntegerStream(DataSource):
    @classmethod
    def name(cls) -> str:
        return "integer_stream"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> _Reader:
        return _Reader(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(IntegerStream)
