"""The proportional reservoir as a table function: PARTITION BY a stratum, ORDER BY arrival."""

from __future__ import annotations

import zlib

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="stratum string, item long, adjusted double")
class ProportionalReservoir:
    """Rows (stratum, item, weight, m) of one partition, in the order asked for."""

    def __init__(self):
        self.sampler = self.stratum = None

    def eval(self, row):
        from wsample.samplers import ProportionalSampler, keyed_rng

        if self.sampler is None:
            self.stratum = row["stratum"]
            self.sampler = ProportionalSampler(row["m"], keyed_rng(zlib.crc32(str(self.stratum).encode())))
        self.sampler.feed(row["item"], float(row["weight"]))

    def terminate(self):
        if self.sampler is not None:
            for e in self.sampler.snapshot():
                yield self.stratum, e.item, e.key


def register(spark: SparkSession) -> None:
    spark.udtf.register("proportional_reservoir", ProportionalReservoir)
