"""A data source of test operators: spark.read.format('spectral').option('kind', ...).option('n', ...)."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Rows(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class SpectralReader(DataSourceReader):
    def __init__(self, options: dict):
        self.kind, self.n = options.get("kind", "onetwoone"), int(options.get("n", 100))
        self.parts = int(options.get("partitions", 4))
        self.dmax, self.eps = float(options.get("dmax", 1.0)), float(options.get("eps", 1e-4))
        if self.kind not in ("onetwoone", "wilkinson", "uniform", "geometric"):
            raise ValueError(f"unknown kind: {self.kind}")

    def partitions(self) -> list[Rows]:
        step = -(-self.n // max(1, self.parts))
        return [Rows(a, min(self.n, a + step)) for a in range(0, self.n, step)] or [Rows(0, 0)]

    def diagonal(self, i: int) -> float:
        n = self.n
        if self.kind == "onetwoone":
            return 2.0
        if self.kind == "wilkinson":
            return abs(i - (n - 1) / 2)
        if self.kind == "uniform":
            return self.dmax * (self.eps + i * (1 - self.eps) / max(1, n - 1))
        return self.dmax * self.eps ** ((n - 1 - i) / max(1, n - 1))

    def read(self, partition: Rows) -> Iterator[tuple]:
        banded = self.kind in ("onetwoone", "wilkinson")
        for i in range(partition.low, partition.high):
            if banded and i:
                yield i, i - 1, 1.0
            yield i, i, float(self.diagonal(i))
            if banded and i + 1 < self.n:
                yield i, i + 1, 1.0


class SpectralSource(DataSource):
    """Coordinates (i, j, v): tridiagonal families, or diagonal operators with the uniform or geometric spectrum."""

    @classmethod
    def name(cls) -> str:
        return "spectral"

    def schema(self) -> str:
        return "i long, j long, v double"

    def reader(self, schema) -> SpectralReader:
        return SpectralReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SpectralSource)
