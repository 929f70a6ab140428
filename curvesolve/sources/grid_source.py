"""A Python data source that yields the cells of a grid: spark.read.format("grid_cells").option("levels", "3,3")."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Part(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, extents: tuple[int, ...], parts: int):
        self.extents, self.parts = extents, parts

    def partitions(self) -> list[_Part]:
        n = 1
        for e in self.extents:
            n *= e
        step = -(-n // self.parts)
        return [_Part(a, min(n, a + step)) for a in range(0, n, step)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        for number in range(partition.lo, partition.hi):
            rest, k = number, []
            for e in reversed(self.extents):
                rest, c = divmod(rest, e)
                k.append(c + 1)
            yield number, k[::-1]


class GridCells(DataSource):
    @classmethod
    def name(cls) -> str:
        return "grid_cells"

    def schema(self) -> str:
        return "id bigint, k array<int>"

    def reader(self, schema) -> _Reader:
        levels = [int(x) for x in self.options["levels"].split(",")]
        return _Reader(tuple(2**k - 1 for k in levels), int(self.options.get("parts", "4")))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GridCells)
