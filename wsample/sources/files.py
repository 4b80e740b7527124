"""Readers and writers of samples and populations."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession

FORMATS = ("parquet", "orc", "json", "csv")


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema=None, **options) -> DataFrame:
    """Text formats need their schema, so that nothing is inferred by an extra pass."""
    if fmt not in FORMATS:
        raise ValueError(f"unknown format: {fmt!r}")
    reader = spark.read.options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    elif fmt in ("json", "csv"):
        raise ValueError("text formats need a schema")
    return reader.format(fmt).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", *, by: Sequence[str] = (), mode: str = "errorifexists", **options) -> None:
    """Partitioned by stratum where asked."""
    writer = df.write.mode(mode).options(**options).format(fmt)
    (writer.partitionBy(*by) if by else writer).save(path)


def append_reservoir(df: DataFrame, path: str, batch: int) -> None:
    """One reservoir a batch in a log; the same batch again replaces its own."""
    df.write.mode("overwrite").parquet(f"{path}/batch={batch}")


def kafka_stream(spark: SparkSession, servers: str, topic: str, **options) -> DataFrame:
    """A Kafka topic's values as text; needs the connector on the class path."""
    return spark.readStream.format("kafka").option("kafka.bootstrap.servers", servers).option("subscribe", topic).options(**options).load().selectExpr("CAST(value AS STRING) AS value", "timestamp")
