"""Draw role with bounded multiplicity: an item takes at most k slots, or its own number of them.

Slot j goes to the earliest finisher of race j among items that hold fewer than their share of earlier slots.  At most
(j - 1) // k items are used up by then, so a slot's best (j - 1) // k + 1 keys hold its winner.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wsample.functions.randomness import keyed_uniform
from wsample.functions.weights import positive_weight
from wsample.operators.race import group_limit, surviving
from wsample.samplers import BoundedSampler


def slot_candidates(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], k: int | Column, seed: int, tag: str, source: str, on_bad_weight: str, least_k: int = 1) -> DataFrame:
    """(slot, item, k, e, r): each slot's best keys; the plan cuts every slot to them before the shuffle."""
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    share = (F.lit(k) if isinstance(k, int) else k).cast("int")
    each = good.select(*id_cols, w.alias("w"), share.alias("k"), F.explode(F.sequence(F.lit(1), F.lit(m))).alias("slot")).where("k > 0")
    keyed = each.withColumn("e", -F.ln(keyed_uniform([*id_cols, "slot"], seed=seed, tag=tag, source=source)) / F.col("w"))
    ranked = keyed.withColumn("r", F.row_number().over(Window.partitionBy("slot").orderBy("e", *id_cols)))
    most = (m - 1) // least_k + 1
    if most > group_limit(df):
        keyed = surviving(keyed, most, ["slot"], key="e")
        ranked = keyed.withColumn("r", F.row_number().over(Window.partitionBy("slot").orderBy("e", *id_cols)))
    return ranked.where(F.col("r") <= most).where(F.col("r") <= F.floor((F.col("slot") - 1) / least_k) + 1)


def bounded_sample(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], k: int | Column = 2, method: str = "candidates", seed: int = 0, tag: str = "bound", source: str = "xxhash", on_bad_weight: str = "error", engine: str = "race") -> DataFrame:
    """(slot, ids, copy_no).  ``candidates`` resolves at most m(m + 1) / 2 keys; ``pipeline`` runs the chain of samplers in one task,
    samplers of one by the ``engine``: race or proportional.

    With k of m it is sampling with replacement, with k of 1 the draw role.  Slots that nobody may take are left out.
    """
    kinds = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in id_cols)
    schema = f"slot int, {kinds}, copy_no int"
    least = k if isinstance(k, int) else 1
    if m <= 0 or least <= 0:
        return df.sparkSession.createDataFrame([], schema)
    if method == "pipeline":
        return _pipeline(df, m, weight, list(id_cols), k, seed, tag, source, on_bad_weight, schema, engine)
    if engine != "race":
        raise ValueError("other engines need the pipeline")
    found = slot_candidates(df, m, weight=weight, id_cols=id_cols, k=k, seed=seed, tag=tag, source=source, on_bad_weight=on_bad_weight, least_k=least)

    def resolve(batches):
        used: dict[tuple, int] = {}
        taken, slot, items, copies = set(), [], [], []
        for batch in batches:
            ids = list(zip(*(batch.column(c).to_pylist() for c in id_cols), strict=True))
            for j, item, share in zip(batch.column("slot").to_pylist(), ids, batch.column("k").to_pylist(), strict=True):
                if j not in taken and used.get(item, 0) < share:
                    used[item] = used.get(item, 0) + 1
                    taken.add(j)
                    slot.append(j)
                    items.append(item)
                    copies.append(used[item])
        if slot:
            columns = zip(*items, strict=True)
            kinds_ = [batch.schema.field(c).type for c in id_cols]
            yield pa.RecordBatch.from_arrays([pa.array(slot, pa.int32()), *[pa.array(c, t) for c, t in zip(columns, kinds_, strict=True)], pa.array(copies, pa.int32())], ["slot", *id_cols, "copy_no"])

    return found.select("slot", "e", "k", *id_cols).repartition(1).sortWithinPartitions("slot", "e", *id_cols).mapInArrow(resolve, schema)


def _pipeline(df, m, weight, id_cols, k, seed, tag, source, on_bad_weight, schema, engine):
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    u = F.array(*[keyed_uniform([*id_cols, F.lit(j)], seed=seed, tag=tag, source=source) for j in range(1, m + 1)])
    rows = good.select(*id_cols, w.alias("__w"), (F.lit(k) if isinstance(k, int) else k).cast("int").alias("__k"), u.alias("__u"))

    def chain(batches):
        sampler, kinds = BoundedSampler(m, engine=engine), None
        for batch in batches:
            kinds = [batch.schema.field(c).type for c in id_cols]
            ids = list(zip(*(batch.column(c).to_pylist() for c in id_cols), strict=True))
            sampler.offer(ids, batch.column("__w").to_numpy(), np.stack(batch.column("__u").to_numpy(zero_copy_only=False)) if batch.num_rows else [], batch.column("__k").to_pylist())
        held, out = {}, []
        for j, s in enumerate(sampler.slot, 1):
            if s is not None:
                item = sampler.item[s[1]][0]
                held[item] = held.get(item, 0) + 1
                out.append((j, item, held[item]))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array([j for j, _, _ in out], pa.int32()), *[pa.array(c, t) for c, t in zip(zip(*[i for _, i, _ in out], strict=True), kinds, strict=True)], pa.array([c for _, _, c in out], pa.int32())], ["slot", *id_cols, "copy_no"])

    return rows.coalesce(1).sortWithinPartitions(*id_cols).mapInArrow(chain, schema)
