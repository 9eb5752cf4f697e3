"""A data source of simulated noise cells: ``spark.read.format("dagsim").option("n", ...).option("d", ...).load()``."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Rows(InputPartition):
    def __init__(self, first: int, past: int):
        self.first, self.past = first, past


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.n, self.d, self.seed = int(options.get("n", 100)), int(options.get("d", 10)), int(options.get("seed", 7))
        self.parts, self.kind = int(options.get("partitions", 4)), options.get("noise", "gauss")

    def partitions(self):
        step = -(-self.n // self.parts)
        return [_Rows(i, min(self.n, i + step)) for i in range(0, self.n, step)]

    def read(self, partition):
        import numpy as np

        for i in range(partition.first, partition.past):
            r = np.random.default_rng([self.seed, i])
            x = {"gauss": r.standard_normal, "exp": r.standard_exponential, "gumbel": lambda size: r.gumbel(size=size)}[self.kind](self.d)
            for j, v in enumerate(x):
                yield i, j, float(v)


class SimulatedCells(DataSource):
    @classmethod
    def name(cls) -> str:
        return "dagsim"

    def schema(self) -> str:
        return "sample_id long, node_id int, x double"

    def reader(self, schema):
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SimulatedCells)
