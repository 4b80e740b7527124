"""What the samplers are held against."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsample.functions.randomness import keyed_uniform
from wsample.functions.weights import positive_weight
from wsample.operators.inclusion import threshold
from wsample.operators.prefix import running
from wsample.operators.race import race_sample, uniform_sample
from wsample.operators.replacement import slot_uniforms


__all__ = ["expanded_sample", "poisson_sample", "sequential_draw", "spark_samples", "systematic_sample", "uniform_jump_sample", "uniform_sample"]


def sequential_draw(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], order_by: Sequence[str] | None = None, seed: int = 0, tag: str = "round", on_bad_weight: str = "error") -> DataFrame:
    """(round, ids): the definition of the draw role, a round at a time over what is left.  A job a round; for small tables."""
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    left = good.select(*id_cols, w.alias("__w"))
    drawn = []
    for r, u in enumerate(slot_uniforms(m, seed, tag), 1):
        total = left.agg(F.sum("__w")).first()[0]
        if total is None:
            break
        sums = running(left, order_by or list(id_cols), {"__run": F.col("__w")})
        hit = sums.where(F.col("__run") > F.lit(u * total)).orderBy("__run").select(*id_cols).first()
        hit = hit or sums.orderBy(F.desc("__run")).select(*id_cols).first()  # the product may round up to the total
        drawn.append((r, *hit))
        left = left.where(~_same(id_cols, hit))
    kinds = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in id_cols)
    return df.sparkSession.createDataFrame(drawn, f"round int, {kinds}")


def _same(id_cols: Sequence[str], row) -> Column:
    out = F.lit(True)
    for c, v in zip(id_cols, row, strict=True):
        out = out & (F.col(c) == F.lit(v))
    return out


def expanded_sample(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], copies: int | None = None, **kw) -> DataFrame:
    """(ids, copy, position): the draw role over a population with every item ``copies`` (m) times; not sampling with replacement."""
    many = df.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(copies or m))))
    return race_sample(many, m, weight=weight, id_cols=[*id_cols, "copy"], **kw).select(*id_cols, "copy", "position")


def poisson_sample(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], seed: int = 0, tag: str = "poisson", source: str = "xxhash", on_bad_weight: str = "error", tau: float | None = None) -> DataFrame:
    """Items kept on their own with their inclusion chance: m of them on average; a filter once the threshold is known (or given)."""
    if tau is None:
        tau, _ = threshold(df, m, weight=weight, on_bad_weight=on_bad_weight)
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    return good.where(keyed_uniform(list(id_cols), seed=seed, tag=tag, source=source) * F.lit(tau) < w)


def systematic_sample(df: DataFrame, m: int, *, units: Column, id_cols: Sequence[str], order_by: Sequence[str] | None = None, seed: int = 0, tag: str = "grid") -> DataFrame:
    """Items over which the running sum of integer ``units`` crosses one of m evenly spaced points: exactly m, if none is overweight."""
    total = df.agg(F.sum(units)).first()[0]
    if not total or m <= 0:
        return df.limit(0)
    u = int(slot_uniforms(1, seed, tag)[0] * total)
    sums = running(df.withColumn("__c", units), order_by or list(id_cols), {"__csum": F.col("__c")})
    crossed = lambda c: F.floor((c.cast("decimal(20,0)") * F.lit(m) + F.lit(u).cast("decimal(20,0)")) / F.lit(total).cast("decimal(20,0)"))
    return sums.where(crossed(F.col("__csum")) > crossed(F.col("__csum") - F.col("__c"))).drop("__c", "__csum")


def uniform_jump_sample(df: DataFrame, m: int, *, id_cols: Sequence[str], seed: int = 0) -> DataFrame:
    """Equal weights with jumps, a reservoir a task, merged by time."""
    from wsample.operators.kernels import race_kernel

    return race_kernel(df, m, weight=F.lit(1.0), id_cols=id_cols, seed=seed, jump=True)


def spark_samples(df: DataFrame, fraction: float, seed: int = 0) -> dict[str, DataFrame]:
    """Spark's own samplers: unweighted, by fraction, of no fixed size."""
    df.createOrReplaceTempView("__contrast")
    sql = df.sparkSession.sql
    return {
        "sample": df.sample(fraction=fraction, seed=seed), "sample_replacement": df.sample(withReplacement=True, fraction=fraction, seed=seed), "random_split": df.randomSplit([fraction, 1 - fraction], seed=seed)[0],
        "tablesample_percent": sql(f"SELECT * FROM __contrast TABLESAMPLE ({100 * fraction} PERCENT) REPEATABLE ({seed})"), "tablesample_rows": sql("SELECT * FROM __contrast TABLESAMPLE (10 ROWS)"), "tablesample_bucket": sql("SELECT * FROM __contrast TABLESAMPLE (BUCKET 1 OUT OF 10)"),
    }


