"""Race reservoirs as Arrow kernels: one a task, merged by a global top m."""

from __future__ import annotations

from collections.abc import Sequence

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsample.functions.randomness import keyed_uniform
from wsample.functions.weights import positive_weight
from wsample.operators.race import top_m
from wsample.samplers import RaceJumpSampler, RaceSampler, keyed_rng


def race_kernel(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], seed: int = 0, tag: str = "race", source: str = "xxhash", on_bad_weight: str = "error", jump: bool = False) -> DataFrame:
    """(ids, position).  Without jumps the uniforms are keyed, so the result is that of the batch plan; with jumps a task's generator is."""
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    rows = good.select(*id_cols, w.alias("__w"), keyed_uniform(list(id_cols), seed=seed, tag=tag, source=source).alias("__u"))
    kinds = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in id_cols)

    def keep(batches):
        sampler = (RaceJumpSampler if jump else RaceSampler)(m, keyed_rng(seed, TaskContext.get().partitionId()))
        ids: dict[int, tuple] = {}  # of the items kept, by their number in the task
        types = None
        for batch in batches:
            types = [batch.schema.field(c).type for c in id_cols]
            base, before = sampler.seen, sampler.insertions
            sampler.offer(range(base, base + batch.num_rows), batch.column("__w").to_numpy(), None if jump else batch.column("__u").to_numpy())
            if sampler.insertions > before:
                kept = [x[2] for x in sampler.heap]
                new = [i for i in kept if i >= base]
                rows = pa.array([i - base for i in new], pa.int64())
                found = zip(new, zip(*(batch.column(c).take(rows).to_pylist() for c in id_cols), strict=True), strict=True)
                ids = {i: ids[i] for i in kept if i < base} | dict(found)
        kept = sampler.snapshot()
        if kept:
            columns = zip(*[ids[e.item] for e in kept], strict=True)
            yield pa.RecordBatch.from_arrays([*[pa.array(c, t) for c, t in zip(columns, types, strict=True)], pa.array([e.key for e in kept])], [*id_cols, "race_key"])

    return top_m(rows.mapInArrow(keep, f"{kinds}, race_key double"), m, id_cols).drop("race_key")


def work(df: DataFrame, m: int, *, weight: Column | str, variant: str, seed: int = 0) -> DataFrame:
    """(task, seen, draws, insertions, heap_steps) of one variant's reservoirs, one row a task."""
    from wsample.samplers import ProportionalJumpSampler, ProportionalSampler

    kinds = {"race": RaceSampler, "race_jump": RaceJumpSampler, "proportional": ProportionalSampler, "proportional_jump": ProportionalJumpSampler}
    good, w = positive_weight(df, weight)

    def count(batches):
        task = TaskContext.get().partitionId()
        sampler, base = kinds[variant](m, keyed_rng(seed, task)), 0
        for batch in batches:
            sampler.offer(range(base, base + batch.num_rows), batch.column(0).to_numpy())
            base += batch.num_rows
        yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in (task, sampler.seen, sampler.draws, sampler.insertions, sampler.heap_steps)], ["task", "seen", "draws", "insertions", "heap_steps"])

    return good.select(w.alias("w")).mapInArrow(count, "task long, seen long, draws long, insertions long, heap_steps long")


def totals(counted: DataFrame) -> DataFrame:
    return counted.agg(*[F.sum(c).alias(c) for c in ("seen", "draws", "insertions", "heap_steps")])
