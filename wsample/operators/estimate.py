"""Population estimates from samples."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsample.operators.race import KEY, race_sample


def estimate_total(sample: DataFrame, y: Column, *, chance: Column | str = "inclusion_prob", by: Sequence[str] = ()) -> DataFrame:
    """(by, n_sample, estimate, std_error): sums of y / chance, with the error of independent inclusion."""
    p = F.col(chance) if isinstance(chance, str) else chance
    return sample.groupBy(*by).agg(F.count("*").alias("n_sample"), F.sum(y / p).alias("estimate"), F.sqrt(F.sum((1 - p) * (y / p) * (y / p))).alias("std_error"))


def draw_sample_with_chances(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], **kw) -> DataFrame:
    """A draw-role sample of m with chances given the time of the next finisher: 1 - exp(-weight * time)."""
    w = F.col(weight) if isinstance(weight, str) else weight
    more = race_sample(df, m + 1, weight=weight, id_cols=id_cols, with_diagnostics=True, **kw)
    last = more.where(F.col("position") == m + 1).select(F.col(KEY).alias("__t"))
    return more.where(F.col("position") <= m).join(F.broadcast(last), how="left").withColumn("inclusion_prob", F.coalesce(1 - F.exp(-w * F.col("__t")), F.lit(1.0))).drop("__t")
