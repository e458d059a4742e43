"""``spark.read.format("lattice")``: nodes of a level band, generated by the reader."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _Reader(DataSourceReader):
    def __init__(self, n: int, low: int, high: int, parts: int):
        self.n, self.low, self.high, self.parts = n, low, high, parts

    def partitions(self):
        size = 1 << self.n
        step = -(-size // self.parts)
        return [_Range(max(1, a), min(size, a + step)) for a in range(0, size, step)]

    def read(self, partition):
        for m in range(partition.low, partition.high):
            if self.low <= m.bit_count() <= self.high:
                yield (m, m.bit_count())


class LatticeSource(DataSource):
    """Options: n (features), low, high (levels), partitions."""

    @classmethod
    def name(cls) -> str:
        return "lattice"

    def schema(self) -> str:
        return "mask long, level int"

    def reader(self, schema) -> DataSourceReader:
        n = int(self.options["n"])
        return _Reader(n, int(self.options.get("low", 1)), int(self.options.get("high", n)), int(self.options.get("partitions", 4)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(LatticeSource)
