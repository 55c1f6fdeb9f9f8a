"""A data source that makes random edges in parallel: ``spark.read.format("edge_generator")`` after ``register(spark)``."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class EdgeGenerator(DataSource):
    """Options: edges, levels (2^levels ids), skew (weight of the first quadrant against 3), partitions, seed."""

    @classmethod
    def name(cls) -> str:
        return "edge_generator"

    def schema(self) -> str:
        return "a long, b long"

    def reader(self, schema) -> DataSourceReader:
        return EdgeReader(self.options)


class EdgeReader(DataSourceReader):
    def __init__(self, options):
        get = lambda k, v: int(options.get(k, v))
        self.edges, self.levels, self.skew, self.parts, self.seed = get("edges", 1000), get("levels", 10), get("skew", 3), get("partitions", 4), get("seed", 42)

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa

        i = partition.value
        left = self.edges // self.parts + (i < self.edges % self.parts)
        rng = np.random.default_rng([self.seed, i])
        first = self.skew / (self.skew + 3)
        while left:
            n = min(left, 1 << 16)
            q = rng.choice(4, (n, self.levels), p=[first, *[(1 - first) / 3] * 3])
            bits = 1 << np.arange(self.levels)
            yield pa.RecordBatch.from_arrays([pa.array(((q >> 1) * bits).sum(1)), pa.array(((q & 1) * bits).sum(1))], names=["a", "b"])
            left -= n


def register(spark: SparkSession) -> None:
    spark.dataSource.register(EdgeGenerator)
