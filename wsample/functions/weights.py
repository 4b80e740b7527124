"""Weight expressions and the policy for weights that are not positive reals."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def as_column(x: Column | str | float) -> Column:
    if isinstance(x, str):
        return F.col(x)
    return x if isinstance(x, Column) else F.lit(float(x))


def is_good(weight: Column | str) -> Column:
    """True where the weight is a finite number above zero."""
    w = as_column(weight).cast("double")
    return F.coalesce(w.isNotNull() & ~F.isnan(w) & (w > 0) & (w < F.lit(float("inf"))), F.lit(False))


def positive_weight(df: DataFrame, weight: Column | str, *, on_bad_weight: str = "error") -> tuple[DataFrame, Column]:
    """``df`` and a double weight expression, with bad rows dropped or made to raise when they are read.

    Dropping keeps the plain comparison in the filter, so that it reaches the Parquet scan.
    """
    w = as_column(weight).cast("double")
    if on_bad_weight == "drop":
        return df.where(is_good(weight)), w
    if on_bad_weight == "error":
        return df, F.when(is_good(weight), w).otherwise(F.raise_error(F.lit("weight is not a positive real")).cast("double"))
    raise ValueError(f"on_bad_weight must be 'error' or 'drop', not {on_bad_weight!r}")


def cents(x: Column | str) -> Column:
    """Money as an integer, for exact sums and comparisons."""
    return F.round(as_column(x) * 100).cast("long")
