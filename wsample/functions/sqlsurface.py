"""SQL scalar functions of the samplers, inlined by the analyzer."""

from __future__ import annotations

from pyspark.sql import SparkSession


def register(spark: SparkSession) -> None:
    """keyed_hash52(text), keyed_uniform(text), race_key_log(text, weight), race_key_gumbel(text, log_weight); text is seed|tag|ids."""
    for body in (
        "keyed_hash52(t STRING) RETURNS BIGINT RETURN CAST(conv(substr(md5(t), 1, 13), 16, 10) AS BIGINT)",
        "keyed_uniform(t STRING) RETURNS DOUBLE RETURN (CAST(conv(substr(md5(t), 1, 13), 16, 10) AS BIGINT) + CAST(0.5 AS DOUBLE)) / CAST(4503599627370496 AS DOUBLE)",
        "race_key_log(t STRING, w DOUBLE) RETURNS DOUBLE RETURN -ln((CAST(conv(substr(md5(t), 1, 13), 16, 10) AS BIGINT) + CAST(0.5 AS DOUBLE)) / CAST(4503599627370496 AS DOUBLE)) / w",
        "race_key_gumbel(t STRING, lw DOUBLE) RETURNS DOUBLE RETURN ln(-ln((CAST(conv(substr(md5(t), 1, 13), 16, 10) AS BIGINT) + CAST(0.5 AS DOUBLE)) / CAST(4503599627370496 AS DOUBLE))) - lw",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {body}")
