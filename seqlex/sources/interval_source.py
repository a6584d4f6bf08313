"""A reader of tab-separated interval files that takes filters on the contig and the category itself."""

from __future__ import annotations

import glob
import os
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, InputPartition

SPLIT_BYTES = 64 << 20
FIELDS = {("contig",): 0, ("category",): 3}


@dataclass
class Span(InputPartition):
    path: str
    begin: int
    end: int


class IntervalReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.paths = sorted(p for p in glob.glob(os.path.join(options["path"], "*") if os.path.isdir(options["path"]) else options["path"]) if os.path.isfile(p))
        self.split = int(options.get("splitBytes", SPLIT_BYTES))
        self.wanted: list[tuple[int, str]] = []

    def pushFilters(self, filters) -> Iterator:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute in FIELDS:
                self.wanted.append((FIELDS[f.attribute], f.value))
            else:
                yield f

    def partitions(self) -> list[Span]:
        return [Span(p, a, a + self.split) for p in self.paths for a in range(0, max(1, os.path.getsize(p)), self.split)]

    def read(self, span: Span) -> Iterator[tuple]:
        """A line belongs to the span that holds its first byte."""
        with open(span.path, "rb") as f:
            if span.begin:
                f.seek(span.begin - 1)
                f.readline()
            while f.tell() < span.end and (line := f.readline()):
                cells = line.decode().rstrip("\r\n").split("\t")
                if len(cells) >= 4 and all(cells[k] == v for k, v in self.wanted):
                    yield cells[0], int(cells[1]), int(cells[2]), cells[3]


class IntervalSource(DataSource):
    """Options: path (a file, a folder or a pattern that the driver and all executors can open) and splitBytes. Lines of fewer than four cells are passed over."""

    @classmethod
    def name(cls) -> str:
        return "intervals"

    def schema(self) -> str:
        return "contig string, start long, end long, category string"

    def reader(self, schema) -> IntervalReader:
        return IntervalReader(self.options)


def read_interval_files(spark: SparkSession, path: str, **options) -> DataFrame:
    """(contig, start, end, category). Equality filters on contig and category are applied while reading."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(IntervalSource)
    return spark.read.format("intervals").options(path=path, **options).load()
