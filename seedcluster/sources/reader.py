"""A Python data source for adjacency lines: line i of a file holds the neighbours of node i."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Lines(InputPartition):
    """Bytes from..to of a file, whose first whole line has this number."""

    def __init__(self, path: str, start: int, end: int, first: int):
        self.path, self.start, self.end, self.first = path, start, end, first


class AdjacencyReader(DataSourceReader):
    """Cuts a file into ranges of bytes. One pass over the file on the driver counts line ends, a block at a time, and keeps two numbers a range."""

    def __init__(self, options: dict):
        self.path = options["path"].removeprefix("file://")
        self.first, self.part, self.block = int(options.get("first", 1)), int(options.get("partbytes", 64 << 20)), 1 << 20

    def partitions(self) -> list[Lines]:
        out, start, at, line, begin = [], 0, 0, self.first, self.first
        with open(self.path, "rb") as f:
            while block := f.read(self.block):
                if at + len(block) - start >= self.part and (cut := block.rfind(b"\n") + 1):
                    out.append(Lines(self.path, start, at + cut, begin))
                    start, begin = at + cut, line + block.count(b"\n", 0, cut)
                line += block.count(b"\n")
                at += len(block)
        return [*out, Lines(self.path, start, at, begin)] if at > start else out

    def read(self, part: Lines) -> Iterator[tuple]:
        with open(part.path, "rb") as f:
            f.seek(part.start)
            number = part.first
            while f.tell() < part.end and (line := f.readline()):
                for x in line.split():
                    yield number, int(x)
                number += 1


class AdjacencyLines(DataSource):
    """(line, nbr) of each neighbour. Options: path (a file that all executors see), first (number of the first line), partBytes (bytes a task reads)."""

    @classmethod
    def name(cls) -> str:
        return "adjacency_lines"

    def schema(self) -> str:
        return "line bigint, nbr bigint"

    def reader(self, schema) -> AdjacencyReader:
        return AdjacencyReader({k.lower(): v for k, v in self.options.items()})


def register(spark: SparkSession) -> None:
    spark.dataSource.register(AdjacencyLines)
