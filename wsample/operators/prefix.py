"""Running sums over a total order without pulling the table into one task."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ByteType, IntegerType, LongType, ShortType

from wsample.plans.shared import written

#: Bits of a row's place within its task, as monotonically_increasing_id lays them out.
PLACE = 33


def _starts(rows: DataFrame, sums: Sequence[str], tops: Sequence[str]) -> DataFrame:
    """What is before each task: rows, sums and maxima; one row a task."""
    part = F.shiftright("__at", PLACE).alias("__part")
    ends = [F.max_by(f"__hi_{k}", "__at").alias(f"__e_{k}") for k in sums]
    totals = rows.groupBy(part).agg(F.count("*").alias("__n"), *ends, *[F.max(f"__x_{k}").alias(f"__m_{k}") for k in tops])
    before = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    return totals.select("__part", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__n0"), *[F.coalesce(F.sum(f"__e_{k}").over(before), F.lit(0)).alias(f"__s_{k}") for k in sums], *[F.max(f"__m_{k}").over(before).alias(f"__b_{k}") for k in tops])


def running(df: DataFrame, order: Sequence[Column | str], values: dict[str, Column], *, largest: dict[str, Column] | None = None, number: str | None = None, lower: bool = False) -> DataFrame:
    """``df`` with inclusive running sums (``values``), running maxima (``largest``) and a 1-based row number over ``order``.

    The dealt rows are written once and read back: range bounds come from a sample and tasks are merged at run time, so a plan
    that dealt the rows twice would not deal them alike.  One range shuffle: a task's running values are made where its rows are sorted and written with them; the totals of the
    tasks (one row each) then give every task its start.  Order columns must be a total order; select the columns needed
    first, as all of ``df`` is written.  Integers are summed as longs, all else as doubles; nulls count as nothing.
    With ``lower``, ``<name>_lower`` is the sum before the row: the very number that the row before it has.
    """
    largest = largest or {}
    kinds = dict(df.select(*[v.alias(k) for k, v in values.items()]).dtypes) if values else {}
    whole = {k for k, f in zip(values, df.select(*values.values()).schema if values else [], strict=True) if isinstance(f.dataType, (ByteType, ShortType, IntegerType, LongType))}
    made = {f"__v_{k}": F.coalesce(v.cast("long" if k in whole else "double"), F.lit(0)) for k, v in values.items()} | {f"__x_{k}": v.cast("double") for k, v in largest.items()}
    rows = df.withColumns(made).repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__at", F.monotonically_increasing_id())
    sums, tops, inputs = list(kinds), list(largest), set(made)
    types = {k: np.int64 if k in whole else np.float64 for k in sums}

    def add(batches):
        upto, top = {k: types[k](0) for k in sums}, dict.fromkeys(tops, -np.inf)
        for batch in batches:
            columns = []
            for k in sums:
                v = batch.column(f"__v_{k}").to_numpy(zero_copy_only=False)
                hi = np.cumsum(np.concatenate([[upto[k]], v]), dtype=types[k])
                if len(v):
                    upto[k] = hi[-1]
                columns += [pa.array(hi[:-1]), pa.array(hi[1:])]
            for k in tops:
                x = np.maximum.accumulate(np.concatenate([[top[k]], np.nan_to_num(batch.column(f"__x_{k}").to_numpy(zero_copy_only=False), nan=-np.inf)]))
                top[k] = x[-1]
                columns.append(pa.array(x[1:]))
            kept = [n for n in batch.schema.names if n not in inputs]
            yield pa.RecordBatch.from_arrays([*[batch.column(n) for n in kept], *columns], [*kept, *names])

    names = [n for k in sums for n in (f"__lo_{k}", f"__hi_{k}")] + [f"__x_{k}" for k in tops]
    if names:
        kept = [f for f in rows.schema if f.name not in made]
        schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept), *(f"`__{e}_{k}` {'long' if k in whole else 'double'}" for k in sums for e in ("lo", "hi")), *(f"`__x_{k}` double" for k in tops)])
        rows = rows.mapInArrow(add, schema)
    rows = written(rows, "steps")
    joined = rows.withColumn("__part", F.shiftright("__at", PLACE)).join(F.broadcast(_starts(rows, sums, tops)), "__part")  # one row a task of the range shuffle
    out = {k: F.col(f"__hi_{k}") + F.col(f"__s_{k}") for k in sums}
    if lower:
        out |= {f"{k}_lower": F.col(f"__lo_{k}") + F.col(f"__s_{k}") for k in sums}
    out |= {k: F.greatest(f"__x_{k}", f"__b_{k}") for k in tops}
    if number:
        out[number] = F.col("__at").bitwiseAND(2**PLACE - 1) + F.col("__n0") + 1
    return joined.withColumns(out).drop("__part", "__at", "__n0", *names, *[f"__s_{k}" for k in sums], *[f"__b_{k}" for k in tops])
