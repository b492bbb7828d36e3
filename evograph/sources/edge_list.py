"""A Python data source for edge lists: one ``src dst [time]`` per line, ``#`` starts a comment."""

from __future__ import annotations

import os
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class EdgeListSource(DataSource):
    """``spark.dataSource.register(EdgeListSource)``, then ``format("edgelist").load(path)``; ``parts`` splits the file by bytes."""

    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> str:
        return "src bigint, dst bigint, time double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"], int(self.options.get("parts", 1)))


class _Part(InputPartition):
    def __init__(self, begin: int, end: int):
        self.begin, self.end = begin, end


class _Reader(DataSourceReader):
    def __init__(self, path: str, parts: int):
        self.path, self.parts = path.removeprefix("file:"), parts

    def partitions(self) -> list[InputPartition]:
        size = os.path.getsize(self.path)
        cuts = [size * k // self.parts for k in range(self.parts + 1)]
        return [_Part(a, b) for a, b in zip(cuts, cuts[1:])]

    def read(self, partition: _Part) -> Iterator[tuple]:
        """Lines that start inside the byte range."""
        with open(self.path, "rb") as f:
            f.seek(partition.begin)
            if partition.begin:
                f.seek(partition.begin - 1)
                f.readline()
            while f.tell() < partition.end:
                line = f.readline()
                if not line:
                    return
                words = line.decode().split("#")[0].split()
                if len(words) >= 2:
                    yield int(words[0]), int(words[1]), float(words[2]) if len(words) > 2 else None
