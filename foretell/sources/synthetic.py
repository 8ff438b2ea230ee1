"""A data source of synthetic labelled matrices: any number of rows, made where they are read.

``spark.read.format("synthetic_matrix").options(rows=..., features=..., noise=..., seed=..., partitions=...)``
gives (row BIGINT, label INT, features ARRAY<DOUBLE>): standard normal features, a planted
hyperplane, labels flipped with probability ``noise``.  A partition is a range of rows and is
drawn from a generator seeded by its first row's block, so reruns of a partition agree.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

BLOCK = 4096


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.rows, self.d = int(options.get("rows", 1000)), int(options.get("features", 10))
        self.noise, self.seed = float(options.get("noise", 0.0)), int(options.get("seed", 0))
        self.parts = int(options.get("partitions", 8))

    def partitions(self) -> list[InputPartition]:
        blocks = -(-self.rows // BLOCK)
        step = max(1, -(-blocks // self.parts))
        return [_Range(b * BLOCK, min(self.rows, (b + step) * BLOCK)) for b in range(0, blocks, step)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        plane = np.random.Generator(np.random.PCG64([self.seed, 1])).standard_normal(self.d)
        for at in range(partition.first, partition.last, BLOCK):
            rng = np.random.Generator(np.random.PCG64([self.seed, 2, at]))
            x = rng.standard_normal((BLOCK, self.d))
            y = (x @ plane > 0) ^ (rng.random(BLOCK) < self.noise)
            for i in range(min(BLOCK, partition.last - at)):
                yield (at + i, int(y[i]), x[i].tolist())


class SyntheticMatrix(DataSource):
    @classmethod
    def name(cls) -> str:
        return "synthetic_matrix"

    def schema(self) -> str:
        return "row bigint, label int, features array<double>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SyntheticMatrix)
