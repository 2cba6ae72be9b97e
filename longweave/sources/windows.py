"""A Python data source: the windows of a sequence, in as many parts as asked."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Part(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class Windows(DataSource):
    """Options rows, win, stride and parts; one row (win, lo, hi) for each window."""

    @classmethod
    def name(cls) -> str:
        return "windows"

    def schema(self) -> str:
        return "win int, lo int, hi int"

    def reader(self, schema) -> DataSourceReader:
        return WindowsReader(self.options)


class WindowsReader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.win, self.stride, self.parts = (int(options.get(k, v)) for k, v in (("rows", 0), ("win", 256), ("stride", 224), ("parts", 4)))
        if not 0 < self.stride < self.win:
            raise ValueError("stride must be positive and below the window")

    def partitions(self) -> list[Part]:
        n = -(-self.rows // self.stride)
        cuts = [n * k // self.parts for k in range(self.parts + 1)]
        return [Part(a, z) for a, z in zip(cuts[:-1], cuts[1:], strict=True) if z > a] or [Part(0, 0)]

    def read(self, part: Part) -> Iterator[tuple]:
        for k in range(part.first, part.last):
            yield k, k * self.stride, min(self.rows, k * self.stride + self.win)
