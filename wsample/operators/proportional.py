"""Inclusion-role sampling: the proportional reservoir as a plan.

``distributed`` keeps one reservoir a task and merges them in a tree over adjusted weights: one pass, no sort, m rows a
task to shuffle.  ``windowed`` follows a given order with running sums: after the last step with an overweight item
acceptance is a comparison of products, and the last writer of each slot stays.  ``sequential`` is the definition in one
task, and ``jump`` the same with jumps.
"""

from __future__ import annotations

import zlib
from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsample.functions.randomness import keyed_uniform
from wsample.functions.weights import positive_weight
from wsample.operators.prefix import running
from wsample.plans.shared import written
from wsample.samplers import ProportionalJumpSampler, ProportionalSampler, keyed_rng

FAN_IN = 64


FIELDS = ["g", "name", "item", "w", "adjusted", "node", "place"]


def _narrow(df: DataFrame, weight, id_cols: Sequence[str], on_bad_weight: str, group: Sequence[str] = (), more: dict[str, Column] | None = None) -> DataFrame:
    """(g, name, item, w): the group, its name as text, the ids and the weight."""
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    g = F.struct(*group) if group else F.struct(F.lit(0).alias("all"))
    return good.select(g.alias("g"), F.to_json(g).alias("name"), F.struct(*id_cols).alias("item"), w.alias("w"), *[c.alias(k) for k, c in (more or {}).items()])


def _schema(rows: DataFrame) -> str:
    kind = lambda c: rows.schema[c].dataType.simpleString()
    return f"g {kind('g')}, name string, item {kind('item')}, w double, adjusted double, node int, place int"


def local_reservoirs(rows: DataFrame, m: int, schema: str, *, seed: int, jump: bool = False) -> DataFrame:
    """One reservoir a group and task: (g, item, w, adjusted, node); its generator is keyed by the group and the task's number.

    Only rows that a reservoir keeps become Python objects.
    """
    kind = ProportionalJumpSampler if jump else ProportionalSampler

    def keep(batches):
        node, struct, group_type = TaskContext.get().partitionId(), None, None
        found: dict[str, tuple] = {}  # group -> (sampler, its value, ids of the items kept by their number)
        for batch in batches:
            struct, group_type = batch.schema.field("item").type, batch.schema.field("g").type
            codes = batch.column("name").dictionary_encode()
            code, w = codes.indices.to_numpy(), batch.column("w").to_numpy()
            for c, name in enumerate(codes.dictionary.to_pylist()):
                at = np.flatnonzero(code == c)
                if name not in found:
                    found[name] = (kind(m, keyed_rng(seed, zlib.crc32(name.encode()), node)), batch.column("g")[int(at[0])].as_py(), {})
                sampler, value, ids = found[name]
                base, before = sampler.seen, sampler.insertions
                sampler.offer(range(base, base + len(at)), w[at])
                if sampler.insertions > before:
                    kept = [i for i, _ in sampler.slots]
                    new = [i for i in kept if i >= base]
                    items = batch.column("item").take(pa.array(at[np.array(new, np.int64) - base])).to_pylist() if new else []
                    found[name] = (sampler, value, {i: ids[i] for i in kept if i < base} | dict(zip(new, items, strict=True)))
        for name, (sampler, value, ids) in found.items():
            kept = sampler.snapshot()
            n = len(kept)
            yield pa.RecordBatch.from_arrays([pa.array([value] * n, group_type), pa.array([name] * n, pa.string()), pa.array([ids[e.item] for e in kept], struct), pa.array([e.weight for e in kept], pa.float64()), pa.array([e.key for e in kept], pa.float64()), pa.array([node] * n, pa.int32()), pa.array(range(n), pa.int32())], FIELDS)

    return rows.select("g", "name", "item", "w").mapInArrow(keep, schema)


def _merging(m: int, seed: int, level: int):
    def merge(key, table):
        adjusted, nodes = table.column("adjusted").to_numpy(), table.column("node").to_numpy()
        order = np.lexsort((table.column("place").to_numpy(), -adjusted, nodes))
        sampler = ProportionalSampler(m, keyed_rng(seed, level, zlib.crc32(key[0].as_py().encode()), key[1].as_py()))
        sampler.offer(order.tolist(), adjusted[order])
        kept = sampler.snapshot()
        at = pa.array([e.item for e in kept], pa.int64())
        some = table.select(["g", "name", "item", "w"]).take(at)
        return pa.table([*some.columns, pa.array([e.key for e in kept], pa.float64()), pa.array([key[1].as_py()] * len(kept), pa.int32()), pa.array(range(len(kept)), pa.int32())], FIELDS)

    return merge


def merge_reservoirs(rows: DataFrame, m: int, schema: str, *, seed: int) -> DataFrame:
    """Merge in a tree: at most FAN_IN reservoirs of a group meet in a task a round; adjusted weights stand for what a reservoir saw.

    The tasks' reservoirs are written first, so that a lost executor cannot change what was drawn.
    """
    rows, level = written(rows, "reservoirs"), 0
    most = rows.agg(F.max("node")).first()[0] or 0
    while level == 0 or most > 0:
        level += 1
        rows = rows.withColumn("up", F.floor(F.col("node") / FAN_IN).cast("int"))
        rows = rows.groupBy("name", "up").applyInArrow(_merging(m, seed, level), schema)
        most //= FAN_IN
    return rows


def proportional_sample(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], mode: str = "distributed", order_by: Sequence[Column | str] | None = None, seed: int = 0, tag: str = "prop", source: str = "xxhash", on_bad_weight: str = "error", with_diagnostics: bool = False) -> DataFrame:
    """(ids[, inclusion_prob, adjusted_weight, is_overweight]) of m items, each with chance min(1, weight / threshold).

    Fewer rows than m: all of them.  ``windowed`` also gives ``slot``.
    """
    if m < 0:
        raise ValueError("sample size is negative")
    if m == 0:
        return df.select(*id_cols).limit(0)
    if mode == "windowed":
        return windowed_sample(df, m, weight=weight, id_cols=id_cols, order_by=order_by or list(id_cols), seed=seed, tag=tag, source=source, on_bad_weight=on_bad_weight)
    if mode in ("sequential", "jump"):
        rows = _narrow(df, weight, id_cols, on_bad_weight, more={"o": F.struct(*(order_by or id_cols))}).coalesce(1)
        rows = rows.sortWithinPartitions("o") if order_by else rows
        found = local_reservoirs(rows, m, _schema(rows), seed=seed, jump=mode == "jump")
    elif mode == "distributed":
        rows = _narrow(df, weight, id_cols, on_bad_weight)
        found = merge_reservoirs(local_reservoirs(rows, m, _schema(rows), seed=seed), m, _schema(rows), seed=seed)
    else:
        raise ValueError(f"unknown mode: {mode!r}")
    out = [F.col(f"item.{c}").alias(c) for c in id_cols]
    if with_diagnostics:
        out += [(F.col("w") / F.col("adjusted")).alias("inclusion_prob"), F.col("adjusted").alias("adjusted_weight"), (F.col("w") >= F.col("adjusted")).alias("is_overweight")]
    return found.select(*out)


def by_group(df: DataFrame, m: int, group: Sequence[str], *, weight: Column | str, id_cols: Sequence[str], seed: int = 0, on_bad_weight: str = "error") -> DataFrame:
    """(group, ids): a proportional reservoir of m items a stratum.

    Every task cuts its own rows to m a stratum before any shuffle, so neither a hot stratum nor the table meets in a task;
    a task holds m rows for each stratum that it sees.
    """
    rows = _narrow(df, weight, id_cols, on_bad_weight, group)
    found = merge_reservoirs(local_reservoirs(rows, m, _schema(rows), seed=seed), m, _schema(rows), seed=seed)
    return found.select(*[F.col(f"g.{c}").alias(c) for c in group], *[F.col(f"item.{c}").alias(c) for c in id_cols])


def windowed_sample(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], order_by: Sequence[Column | str], seed: int = 0, tag: str = "prop", source: str = "xxhash", on_bad_weight: str = "error") -> DataFrame:
    """(slot, ids) under a given total order, from keyed uniforms.

    The steps up to one after the last overweight item are run in one task that holds m rows (with weights that keep items
    overweight to the end, use ``distributed``); all later ones are a filter and one aggregate of m rows.
    """
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    base = good.withColumn("__w", w)
    if all(isinstance(c, str) for c in order_by):
        base = base.select("__w", *dict.fromkeys([*id_cols, *order_by]))
    steps = running(base, order_by, {"__run": F.col("__w")}, largest={"__big": F.col("__w")}, number="__k")
    steps = steps.select(*id_cols, "__w", "__run", "__big", "__k", keyed_uniform([F.lit("u"), *id_cols], seed=seed, tag=tag, source=source).alias("__u"), keyed_uniform([F.lit("v"), *id_cols], seed=seed, tag=tag, source=source).alias("__v"))
    last = steps.where(F.lit(m) * F.col("__big") >= F.col("__run")).agg(F.max("__k")).first()[0] or 0
    until = max(last, m) + 1
    kinds = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in id_cols)

    def begin(batches):
        """One sampler over the early steps; of each batch only the rows that it keeps become Python objects."""
        sampler, types, ids = ProportionalSampler(m), None, {}
        for batch in batches:
            types, base = [batch.schema.field(c).type for c in id_cols], sampler.seen
            sampler.offer(range(base, base + batch.num_rows), batch.column("__w").to_numpy(), (batch.column("__u").to_numpy(), batch.column("__v").to_numpy()))
            kept = [i for i, _ in sampler.slots]
            new = [i for i in kept if i >= base]
            at = pa.array([i - base for i in new], pa.int64())
            ids = {i: ids[i] for i in kept if i < base} | dict(zip(new, zip(*(batch.column(c).take(at).to_pylist() for c in id_cols), strict=True), strict=True))
        kept = [ids[i] for i, _ in sampler.slots]
        if kept:
            yield pa.RecordBatch.from_arrays([pa.array(range(len(kept)), pa.int32()), pa.array([0] * len(kept), pa.int64()), *[pa.array(c, t) for c, t in zip(zip(*kept, strict=True), types, strict=True)]], ["slot", "__k", *id_cols])

    early = steps.where(F.col("__k") <= until).select("__k", "__w", "__u", "__v", *id_cols).repartition(1).sortWithinPartitions("__k")
    held = early.mapInArrow(begin, f"slot int, __k long, {kinds}")
    later = steps.where((F.col("__k") > until) & (F.col("__u") * F.col("__run") < F.lit(m) * F.col("__w"))).select(F.floor(F.col("__v") * m).cast("int").alias("slot"), F.col("__k").cast("long").alias("__k"), *id_cols)
    best = held.unionByName(later).groupBy("slot").agg(F.max_by(F.struct(*id_cols), "__k").alias("item"))
    return best.select("slot", *[F.col(f"item.{c}").alias(c) for c in id_cols])


def attach_payload(df: DataFrame, sample: DataFrame, id_cols: Sequence[str]) -> DataFrame:
    """Whole rows of the sampled ids."""
    return df.join(sample, list(id_cols), "inner")
