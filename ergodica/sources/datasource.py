"""A Python data source ``release_site``: the generator's transitions, one input partition for each range of configurations."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, channels: int, capacity: int, parts: int, speed: float):
        self.channels, self.capacity, self.parts, self.speed = channels, capacity, parts, speed

    def partitions(self) -> list[InputPartition]:
        n = (self.channels + 1) ** 3
        step = -(-n // self.parts)
        return [_Range(a, min(n, a + step)) for a in range(0, n, step)]

    def read(self, partition: _Range) -> Iterator[tuple[int, int, float]]:
        from ergodica.functions.udfs import ReleaseSiteMoves

        moves, b = ReleaseSiteMoves(), self.channels + 1
        for k in range(partition.lo, partition.hi):
            o, i, ci = k // (b * b), k // b % b, k % b
            c = self.channels - o - i - ci
            if c < 0:
                continue
            for ions in range(self.capacity + 1):
                src = k * (self.capacity + 1) + ions
                for dst, p in moves.eval(c, o, i, ci, ions, self.channels, self.capacity, self.speed):
                    yield src, dst, p


class ReleaseSiteSource(DataSource):
    """spark.read.format("release_site").option("channels", 2).option("capacity", 60).option("speed", x).load()"""

    @classmethod
    def name(cls) -> str:
        return "release_site"

    def schema(self) -> str:
        return "src bigint, dst bigint, prob double"

    def reader(self, schema) -> DataSourceReader:
        o = self.options
        return _Reader(int(o["channels"]), int(o["capacity"]), int(o.get("partitions", 8)), float(o["speed"]))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ReleaseSiteSource)
