"""Clouds in files: delimited text, JSON, ORC, and a partitioned text data source named ``xyz``."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

XYZ = "pid long, x double, y double, z double"


def read_xyz(spark: SparkSession, path: str, schema: str = XYZ, sep: str = " ") -> DataFrame:
    """Delimited text; lines that don't parse keep their text in ``_bad``."""
    return spark.read.csv(path, schema=f"{schema}, _bad string", sep=sep, mode="PERMISSIVE", columnNameOfCorruptRecord="_bad")


def read_any(spark: SparkSession, path: str, fmt: str, schema: str = XYZ) -> DataFrame:
    return spark.read.format(fmt).schema(schema).load(path)


class _Lines(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


class XyzSource(DataSource):
    """Plain files of lines ``pid x y z``, cut into byte ranges; reads local or mounted paths given to every executor."""

    @classmethod
    def name(cls) -> str:
        return "xyz"

    def schema(self) -> str:
        return XYZ

    def reader(self, schema: StructType) -> DataSourceReader:
        return _XyzReader(self.options)


class _XyzReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.piece = options["path"], int(options.get("splitbytes", 64 << 20))

    def partitions(self) -> list[InputPartition]:
        from pathlib import Path

        top = Path(self.path)
        files = [top] if top.is_file() else sorted(p for p in top.iterdir() if p.is_file() and p.name[0] not in "._")
        return [_Lines(str(f), s, min(s + self.piece, f.stat().st_size)) for f in files for s in range(0, f.stat().st_size, self.piece)]

    def read(self, part: _Lines) -> Iterator[tuple]:
        with open(part.path, "rb") as f:
            f.seek(max(0, part.start - 1))
            if part.start:
                f.readline()  # the line that began before belongs to the range before
            while f.tell() < part.end:
                fields = f.readline().split()
                if len(fields) >= 4:
                    yield int(fields[0]), *(float(v) for v in fields[1:4])
