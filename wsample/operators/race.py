"""Draw-role sampling without replacement: the race sampler.

Each item finishes an exponential race at time -ln(u) / w; the m earliest win and
their order is the draw order.  Spark keeps m rows a task (``TakeOrderedAndProject``)
and never shuffles the population.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wsample.functions.randomness import keyed_uniform
from wsample.functions.weights import positive_weight
from wsample.operators.prefix import running

KEY = "race_key"
#: Beyond this many winners the driver-side top-k gives way to a threshold filter and a range sort.
BIG_M = 100_000


def race_key(u: Column, weight: Column, *, form: str = "log", log_weight: Column | None = None) -> Column:
    """A key of which the smallest win.

    ``log``: -ln(u)/w.  ``power``: minus u**(1/w), which may underflow for tiny weights.
    ``gumbel``: minus (ln w - ln(-ln u)); takes ``log_weight`` where w itself would overflow.
    """
    if form == "log":
        return -F.ln(u) / weight
    if form == "power":
        return -F.pow(u, F.lit(1.0) / weight)
    if form == "gumbel":
        return F.ln(-F.ln(u)) - (F.ln(weight) if log_weight is None else log_weight)
    raise ValueError(f"unknown key form: {form!r}")


def with_race_key(df: DataFrame, *, weight: Column | str | None, id_cols: Sequence[str], seed: int = 0, tag: str = "race", source: str = "xxhash", form: str = "log", log_weight: Column | None = None, on_bad_weight: str = "error") -> DataFrame:
    """``df`` with its race key; ``weight`` None means equal weights."""
    if weight is None:
        w = F.lit(1.0)
    else:
        df, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    u = keyed_uniform(list(id_cols), seed=seed, tag=tag, source=source)
    return df.withColumn(KEY, race_key(u, w, form=form, log_weight=log_weight))


def group_limit(df: DataFrame) -> int:
    """Up to this rank Spark cuts a ranking window before its shuffle."""
    return int(df.sparkSession.conf.get("spark.sql.optimizer.windowGroupLimitThreshold", "1000"))


def top_m(keyed: DataFrame, m: int, id_cols: Sequence[str], *, key: str = KEY, position: str = "position") -> DataFrame:
    """The m smallest keys with their rank; ties fall to the ids, so placement does not matter."""
    if m < 0:
        raise ValueError("sample size is negative")
    order = [F.col(key).asc(), *[F.col(c).asc() for c in id_cols]]
    best = keyed.orderBy(*order).limit(m)
    return best.withColumn(position, F.row_number().over(Window.orderBy(*order)))


def race_sample(df: DataFrame, m: int, *, weight: Column | str | None, id_cols: Sequence[str], seed: int = 0, tag: str = "race", source: str = "xxhash", form: str = "log", log_weight: Column | None = None, on_bad_weight: str = "error", on_short: str = "all", with_diagnostics: bool = False) -> DataFrame:
    """m winners with ``position`` 1..m (and ``race_key`` with diagnostics).  Fewer rows than m: all, or an error."""
    if m < 0:
        raise ValueError("sample size is negative")
    keyed = with_race_key(df, weight=weight, id_cols=id_cols, seed=seed, tag=tag, source=source, form=form, log_weight=log_weight, on_bad_weight=on_bad_weight)
    out = big_top_m(keyed, m, id_cols) if m > BIG_M else top_m(keyed, m, id_cols)
    if on_short == "error" and out.count() < m:
        raise ValueError("the population has fewer items than the sample")
    return out if with_diagnostics else out.drop(KEY)


def big_top_m(keyed: DataFrame, m: int, id_cols: Sequence[str], *, position: str = "position") -> DataFrame:
    """Top m for an m too large for one task.

    A quantile sketch bounds the m-th key from above; survivors are range-sorted and ranked
    by (partition, place) with the partition sizes as offsets, so that no task sees them all.
    """
    n = keyed.count()
    bound = None
    if n > m:
        share = min(1.0, 1.02 * m / n + 1e-4)
        bound = keyed.select(F.percentile_approx(KEY, share, 100_000).alias("t")).first()["t"]
    kept = keyed if bound is None else keyed.where(F.col(KEY) <= F.lit(bound))
    if bound is not None and kept.count() < m:
        kept = keyed
    ranked = global_rank(kept, [KEY, *id_cols], position)
    return ranked.where(F.col(position) <= m)


def global_rank(df: DataFrame, order: Sequence[str], position: str) -> DataFrame:
    """1-based rank over a total order, by one range shuffle."""
    return running(df, order, {}, number=position).withColumn(position, F.col(position).cast("int"))


def surviving(keyed: DataFrame, m: int, group: Sequence[str], *, key: str = KEY) -> DataFrame:
    """Rows that are among their group's m smallest keys of their task so far: a cut before the shuffle, about m log(n / m) rows a group and task.

    Spark cuts ranks before a shuffle for small m only (``spark.sql.optimizer.windowGroupLimitThreshold``).  A task holds m keys a group.
    """
    named = keyed.withColumn("__g", F.to_json(F.struct(*group)))

    def cut(batches):
        best: dict[str, np.ndarray] = {}
        for batch in batches:
            codes = batch.column("__g").dictionary_encode()
            names, code = codes.dictionary.to_pylist(), codes.indices.to_numpy()
            e, keep = batch.column(key).to_numpy(), np.zeros(batch.num_rows, bool)
            for c, name in enumerate(names):
                rows = np.flatnonzero(code == c)
                held = best.get(name, np.zeros(0))
                if len(held) >= m:
                    rows = rows[e[rows] <= held[-1]]
                held = np.sort(np.concatenate([held, e[rows]]))[:m]
                keep[rows[e[rows] <= held[-1]] if len(held) else rows] = True
                best[name] = held
            yield batch.filter(pa.array(keep)).select(kept)

    kept = keyed.columns
    return named.mapInArrow(cut, keyed.schema)


def race_by_group(df: DataFrame, m: int, group: Sequence[str], *, weight: Column | str | None, id_cols: Sequence[str], seed: int = 0, tag: str = "race", source: str = "xxhash", form: str = "log", on_bad_weight: str = "error") -> DataFrame:
    """One race sample a stratum.  The plan cuts each stratum before the shuffle: to m rows a task, or for large m by :func:`surviving`."""
    keyed = with_race_key(df, weight=weight, id_cols=id_cols, seed=seed, tag=tag, source=source, form=form, on_bad_weight=on_bad_weight)
    if m > group_limit(df):
        keyed = surviving(keyed, m, group)
    w = Window.partitionBy(*group).orderBy(F.col(KEY).asc(), *[F.col(c).asc() for c in id_cols])
    return keyed.withColumn("position", F.row_number().over(w)).where(F.col("position") <= m).drop(KEY)


def race_merge(reservoirs: Sequence[DataFrame], m: int, id_cols: Sequence[str]) -> DataFrame:
    """Merge keyed reservoirs of disjoint populations: the m best of their union."""
    union = reservoirs[0]
    for r in reservoirs[1:]:
        union = union.unionByName(r)
    return top_m(union.drop("position"), m, id_cols)


def uniform_sample(df: DataFrame, m: int, *, id_cols: Sequence[str], **kw) -> DataFrame:
    """All weights equal."""
    return race_sample(df, m, weight=None, id_cols=id_cols, **kw)


def late_payload(df: DataFrame, sample: DataFrame, id_cols: Sequence[str]) -> DataFrame:
    """Fetch whole rows of a sample: its ids are joined back, so that wide columns skip the race."""
    return df.join(sample.select(*id_cols), list(id_cols), "left_semi")


