"""A Python data source of graphs that a rule makes, read in parallel ranges."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Stretch(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class GridSource(DataSource):
    """Edges (src, dst) of a grid: option n gives its side, option parts the number of ranges."""

    @classmethod
    def name(cls) -> str:
        return "grid_graph"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> DataSourceReader:
        return GridReader(int(self.options.get("n", 10)), int(self.options.get("parts", 4)))


class GridReader(DataSourceReader):
    def __init__(self, n: int, parts: int):
        self.n, self.parts = n, parts

    def partitions(self) -> list[Stretch]:
        total = self.n * self.n
        return [Stretch(total * k // self.parts, total * (k + 1) // self.parts) for k in range(self.parts)]

    def read(self, partition: Stretch) -> Iterator[tuple[int, int]]:
        for v in range(partition.lo, partition.hi):
            if v % self.n < self.n - 1:
                yield v, v + 1
            if v < self.n * (self.n - 1):
                yield v, v + self.n


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GridSource)
