"""Recursive-matrix edges as a Spark data source: ``spark.read.format("kron").option("edges", m)``."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def kron_edge(i: int, scale: int) -> tuple[int, int]:
    """The same generator as ``graphs.kron_edges``; its constants are fixed values."""
    m = 2147483647
    x, s, d = (i * 48271 + 69621 * 42 + 1) % m, 0, 0
    for _ in range(scale):
        x = (16807 * ((48271 * x + 11) % m) + 7) % m
        r = x % 100
        s, d = 2 * s + (r >= 76), 2 * d + (57 <= r < 76 or r >= 95)
    return s, d


class _Range(InputPartition):
    def __init__(self, low: int, high: int) -> None:
        self.low, self.high = low, high


class _Reader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.edges, self.scale = int(options.get("edges", "1000")), int(options.get("scale", "8"))
        self.parts = int(options.get("partitions", "4"))

    def partitions(self) -> list[InputPartition]:
        step = -(-self.edges // self.parts)
        return [_Range(i, min(i + step, self.edges)) for i in range(0, self.edges, step)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        for i in range(partition.low, partition.high):
            yield kron_edge(i, self.scale)


class KronSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "kron"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)
