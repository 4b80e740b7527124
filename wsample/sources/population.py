"""A data source of synthetic populations: ids and uniform random weights, read in parallel."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Slice(InputPartition):
    def __init__(self, number: int, start: int, end: int):
        super().__init__(number)
        self.number, self.start, self.end = number, start, end


class PopulationReader(DataSourceReader):
    """Weights are a function of the seed and a fixed block of ids, so the table does not depend on the partitions."""

    BLOCK = 65_536

    def __init__(self, options):
        self.rows, self.parts, self.seed = int(options.get("rows", 1000)), int(options.get("partitions", 8)), int(options.get("seed", 0))
        self.low, self.high = float(options.get("low", 0.0)), float(options.get("high", 1.0))

    def partitions(self):
        blocks = -(-self.rows // self.BLOCK)
        parts = max(1, min(self.parts, blocks))
        edge = [self.BLOCK * (blocks * i // parts) for i in range(parts + 1)]
        return [Slice(i, edge[i], min(edge[i + 1], self.rows)) for i in range(parts)]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa

        for lo in range(partition.start, partition.end, self.BLOCK):
            n = min(self.BLOCK, partition.end - lo)
            rng = np.random.Generator(np.random.Philox(np.random.SeedSequence([self.seed, lo // self.BLOCK])))
            u = (rng.integers(0, 2**52, self.BLOCK)[:n] + 0.5) / 2**52
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(lo, lo + n)), pa.array(self.low + (self.high - self.low) * u)], ["id", "weight"])


class WeightedPopulation(DataSource):
    @classmethod
    def name(cls) -> str:
        return "weighted_population"

    def schema(self) -> str:
        return "id long, weight double"

    def reader(self, schema) -> PopulationReader:
        return PopulationReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(WeightedPopulation)
