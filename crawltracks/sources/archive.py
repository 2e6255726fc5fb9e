"""A Python data source that reads byte ranges of archive files: one partition per archive."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, InputPartition

from crawltracks.operators.fetch import FileRangeReader


class _Archive(InputPartition):
    def __init__(self, name: str, ranges: list[tuple[int, int]]):
        self.name, self.ranges = name, ranges


class ArchiveRangeReader(DataSourceReader):
    """Options: root (folder of archives), ranges (JSON: archive -> list of [offset, length])."""

    def __init__(self, options: dict[str, str]):
        self.root = options["root"]
        self.ranges: dict[str, list[list[int]]] = json.loads(options["ranges"])
        self.only: str | None = None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("archive",):
                self.only = f.value
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        names = [n for n in self.ranges if self.only in (None, n)]
        return [_Archive(n, sorted((o, s) for o, s in self.ranges[n])) for n in names]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        if not isinstance(partition, _Archive):
            return
        reader = FileRangeReader(self.root)
        for offset, length in partition.ranges:
            yield partition.name, offset, length, reader.read(partition.name, offset, length)


class ArchiveRangeSource(DataSource):
    """``spark.read.format("archive_range")``, once registered with ``spark.dataSource.register``."""

    @classmethod
    def name(cls) -> str:
        return "archive_range"

    def schema(self) -> str:
        return "archive string, offset bigint, length bigint, body binary"

    def reader(self, schema) -> DataSourceReader:
        return ArchiveRangeReader(self.options)
