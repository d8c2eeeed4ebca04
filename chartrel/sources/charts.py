"""A batch source of generated charts: ``spark.read.format("charts").option("n", 1000).load()`` after ``register``."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "chart_id long, series_key string, x long, y long"


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.points, self.parts = int(options.get("n", 100)), int(options.get("points", 12)), int(options.get("partitions", 4))
        self.seed = options.get("seed", "0")

    def partitions(self) -> list[_Range]:
        edge = [self.n * k // self.parts for k in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(edge, edge[1:]) if b > a]

    def read(self, partition: _Range) -> Iterator[tuple]:
        for chart in range(partition.lo, partition.hi):
            u = lambda *a: int(hashlib.md5(":".join(map(str, (chart, *a, self.seed))).encode()).hexdigest()[:8], 16)  # noqa: B023, E731
            for s in range(u("series") % 3 + 1):
                slope = u("slope", s) % 3 - 1
                for x in range(self.points):
                    yield chart, "abc"[s], x, slope * x * 100 + u("y", s, x) % 150


class Charts(DataSource):
    """Charts of one to three series with slopes of drawn sign, split into ranges of ids."""

    @classmethod
    def name(cls) -> str:
        return "charts"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(Charts)
