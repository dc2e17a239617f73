"""A Python data source for text edge lists: lines of source, target and snapshot."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class EdgeListSource(DataSource):
    """Option ``paths``: files on a file system that workers mount, joined by commas; one partition each."""

    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> str:
        return "x bigint, y bigint, snap int"

    def reader(self, schema) -> DataSourceReader:
        return _Reader([p for p in self.options["paths"].split(",") if p])


class _Reader(DataSourceReader):
    def __init__(self, paths: list[str]) -> None:
        self.paths = paths

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(p) for p in self.paths]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        with open(partition.value.removeprefix("file:").replace("///", "/"), encoding="utf-8") as f:
            for line in f:
                x, y, snap = line.split()
                yield int(x), int(y), int(snap)
