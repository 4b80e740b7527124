"""Recency bias: weights that grow with arrival time, or that depend on age and anything else."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsample.functions.randomness import keyed_uniform
from wsample.functions.times import micros
from wsample.operators.prefix import running
from wsample.operators.proportional import proportional_sample
from wsample.operators.race import race_sample

LN2 = 0.6931471805599453


def seconds(time: Column | str) -> Column:
    """A timestamp as seconds since 1970, a double."""
    return micros(time) / F.lit(1e6)


def exp_decay(time: Column | str, *, half_life: float, landmark: float = 0.0) -> Column:
    """Log of the factor by which an item of that time outweighs one of the landmark; half_life in seconds."""
    return (seconds(time) - F.lit(landmark)) * F.lit(LN2 / half_life)


def poly_decay(time: Column | str, *, now: float, power: float = 1.0, unit: float = 86400.0) -> Column:
    """(1 + age) ** -power, age in units."""
    return F.pow(1 + (F.lit(now) - seconds(time)) / unit, F.lit(-power))


def window_decay(time: Column | str, *, now: float, span: float) -> Column:
    """Falls in a line to nothing at age ``span``."""
    return F.greatest(F.lit(0.0), 1 - (F.lit(now) - seconds(time)) / span)


def step_decay(time: Column | str, *, now: float, span: float, low: float) -> Column:
    """One up to age ``span``, ``low`` after."""
    return F.when(F.lit(now) - seconds(time) <= span, 1.0).otherwise(low)


def recency_sample(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], log_factor: Column | None = None, factor: Column | None = None, role: str = "draw", seed: int = 0, tag: str = "recent", source: str = "xxhash", mode: str = "distributed", landmark_shift: Column | float = 0.0) -> DataFrame:
    """A sample under weight * factor.  ``log_factor`` keeps the draw role in logarithms, where no factor overflows.

    The inclusion role takes exp(log_factor - landmark_shift), so shift by about the latest time's.  Items of factor 0 drop out.
    """
    w = F.col(weight) if isinstance(weight, str) else weight
    if role == "draw":
        if log_factor is not None:
            return race_sample(df, m, weight=w, id_cols=id_cols, seed=seed, tag=tag, source=source, form="gumbel", log_weight=F.ln(w) + log_factor)
        return race_sample(df, m, weight=w * factor, id_cols=id_cols, seed=seed, tag=tag, source=source, on_bad_weight="drop")
    shift = F.lit(landmark_shift) if isinstance(landmark_shift, (int, float)) else landmark_shift
    scaled = w * (F.exp(log_factor - shift) if log_factor is not None else factor)
    return proportional_sample(df, m, weight=scaled, id_cols=id_cols, seed=seed, tag=tag, mode=mode, on_bad_weight="drop")


def constant_rate_reservoir(df: DataFrame, m: int, p: float, *, id_cols: Sequence[str], order_by: Sequence[Column | str], seed: int = 0, tag: str = "rate", source: str = "xxhash") -> DataFrame:
    """(slot, ids): after the first m each arrival enters with chance p and replaces a uniform slot; a filter and one aggregate of m rows."""
    steps = running(df.select(*dict.fromkeys([*id_cols, *[c for c in order_by if isinstance(c, str)]])), order_by, {}, number="__k")
    u = keyed_uniform([F.lit("u"), *id_cols], seed=seed, tag=tag, source=source)
    v = keyed_uniform([F.lit("v"), *id_cols], seed=seed, tag=tag, source=source)
    slot = F.when(F.col("__k") <= m, F.col("__k") - 1).otherwise(F.floor(v * m)).cast("int")
    entered = steps.where((F.col("__k") <= m) | (u < p)).select(slot.alias("slot"), "__k", F.struct(*id_cols).alias("item"))
    best = entered.groupBy("slot").agg(F.max_by("item", "__k").alias("item"))
    return best.select("slot", *[F.col(f"item.{c}").alias(c) for c in id_cols])
