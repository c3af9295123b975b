"""Generated graphs as data sources: format('torus') and format('rmat')."""

from __future__ import annotations

import hashlib

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from tourspark.session import ship


class _Span(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


def _spans(total: int, parts: int) -> list[_Span]:
    return [_Span(total * i // parts, total * (i + 1) // parts) for i in range(parts)]


class _Torus(DataSourceReader):
    def __init__(self, options):
        self.rows, self.cols = int(options.get("rows", 64)), int(options.get("cols", 64))
        self.parts = int(options.get("parts", 8))

    def partitions(self):
        return _spans(self.rows * self.cols, self.parts)

    def read(self, partition):
        for i in range(partition.low, partition.high):
            r, c = divmod(i, self.cols)
            yield i, r * self.cols + (c + 1) % self.cols
            yield i, (r + 1) % self.rows * self.cols + c


class TorusSource(DataSource):
    """A grid closed both ways. Options: rows, cols, parts."""

    @classmethod
    def name(cls):
        return "torus"

    def schema(self):
        return "u long, v long"

    def reader(self, schema):
        return _Torus(self.options)


class _Rmat(DataSourceReader):
    def __init__(self, options):
        self.scale, self.per = int(options.get("scale", 10)), int(options.get("pervertex", 5))
        a, b, c = (float(options.get(k, d)) for k, d in (("a", 0.57), ("b", 0.19), ("c", 0.19)))
        self.cuts = [round(x * 65536) for x in (a, a + b, a + b + c)]
        self.seed, self.parts = int(options.get("seed", 1)), int(options.get("parts", 8))

    def partitions(self):
        return _spans((1 << self.scale) * self.per, self.parts)

    def read(self, partition):
        for i in range(partition.low, partition.high):
            u = v = 0
            for bit in range(self.scale):
                draw = int(hashlib.md5(f"{self.seed}-{bit}-{i}".encode()).hexdigest()[:4], 16)
                u = u * 2 + (draw >= self.cuts[1])
                v = v * 2 + (self.cuts[0] <= draw < self.cuts[1] or draw >= self.cuts[2])
            yield u, v


class RmatSource(DataSource):
    """A power-law graph by quadrants. Options: scale, pervertex, a, b, c, seed, parts."""

    @classmethod
    def name(cls):
        return "rmat"

    def schema(self):
        return "u long, v long"

    def reader(self, schema):
        return _Rmat(self.options)


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.dataSource.register(TorusSource)
    spark.dataSource.register(RmatSource)
