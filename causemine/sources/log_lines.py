"""A Spark data source for raw log text: lines that begin with a time, from files or handed over."""

from __future__ import annotations

import glob
import os
import re
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

_LINE = re.compile(r"\s*(\d+:\d\d)\s+(.+?)\s*$")


class _Part(InputPartition):
    """Bytes of a file in which the lines begin that a task reads, or a text."""

    def __init__(self, path: str | None, first: int, last: int, text: str = "") -> None:
        self.path, self.first, self.last, self.text = path, first, last, text


class _Reader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.path, self.text = options.get("path"), options.get("text", "")
        self.size = int(options.get("bytesPerPartition", str(64 << 20)))

    def partitions(self) -> list[InputPartition]:
        if not self.path:
            return [_Part(None, 0, 0, self.text)]
        files = sorted(glob.glob(os.path.join(self.path, "*"))) if os.path.isdir(self.path) else sorted(glob.glob(self.path))
        return [_Part(f, i, i + self.size) for f in files for i in range(0, max(1, os.path.getsize(f)), self.size)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        for line in partition.text.split("\n") if partition.path is None else _lines(partition):
            if m := _LINE.match(line):
                yield m[1], m[2]


def _lines(part: _Part) -> Iterator[str]:
    """The lines that begin in the part; the one that is under way at its start belongs to the part before."""
    with open(part.path, "rb") as f:
        f.seek(max(0, part.first - 1))
        if part.first:
            f.readline()
        while f.tell() < part.last and (line := f.readline()):
            yield line.decode("utf-8", "replace").rstrip("\n")


class LogLines(DataSource):
    """format('log_lines').load(path): files of a folder that all executors see, cut into parts; option
    'text' hands lines over instead. Logs in an object store are read with spark.read.text and split
    by `operators.prepare.parse_lines`."""

    @classmethod
    def name(cls) -> str:
        return "log_lines"

    def schema(self) -> str:
        return "time string, message string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(LogLines)
