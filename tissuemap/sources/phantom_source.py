"""The digital phantom as a Python data source: one partition per band of rows."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.phantom import CLASSES, ELLIPSES


class Band(InputPartition):
    def __init__(self, first: int, last: int) -> None:
        self.first, self.last = first, last


class PhantomReader(DataSourceReader):
    def __init__(self, n: int, bands: int) -> None:
        self.n, self.bands = n, bands

    def partitions(self):
        edges = [self.n * i // self.bands for i in range(self.bands + 1)]
        return [Band(a, z) for a, z in zip(edges, edges[1:], strict=False) if z > a]

    def read(self, partition: Band):
        tissue = {c[0]: c[1:] for c in CLASSES}
        for row in range(partition.first, partition.last):
            for col in range(self.n):
                x, y, kind = (col + 0.5) * 2 / self.n - 1, (row + 0.5) * 2 / self.n - 1, None
                for c, cx, cy, ax, ay in ELLIPSES:
                    if ((x - cx) / ax) ** 2 + ((y - cy) / ay) ** 2 <= 1:
                        kind = c
                yield (row, col, kind, *tissue.get(kind, (0.0, 0.0, 0.0)))


class PhantomSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "phantom"

    def schema(self) -> str:
        return "row int, col int, class int, t1 double, t2 double, pd double"

    def reader(self, schema) -> PhantomReader:
        return PhantomReader(int(self.options.get("n", "64")), int(self.options.get("bands", "4")))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PhantomSource)
