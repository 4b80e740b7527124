"""Sampling with replacement: m slots, each drawn by itself in proportion to weight."""

from __future__ import annotations

import hashlib
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
from wsample.samplers import SlotRaces, keyed_rng


def replacement_sample(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], method: str = "auto", order_by: Sequence[Column | str] | None = None, seed: int = 0, tag: str = "slot", source: str = "xxhash", on_bad_weight: str = "error") -> DataFrame:
    """(slot, ids), slots 1..m.  ``race``: n * m keys.  ``race_jump``: a few draws a slot and task.  ``proportional``: last acceptance by running sums.
    ``proportional_jump``: acceptances alone, found in the running sums.  ``lookup``: m uniforms in the running sums.  ``auto``: jumps of the
    race, one pass without a shuffle of rows, up to 1,000 slots; beyond that jumps over the running sums."""
    if method == "auto":
        method = "race_jump" if m <= 1000 else "proportional_jump"
    f = {"race": _race, "race_jump": _race_jump, "proportional": _proportional, "proportional_jump": _proportional_jump, "lookup": _lookup}[method]
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    if m <= 0:
        return good.select(F.lit(1).alias("slot"), *id_cols).limit(0)
    return f(good.withColumn("__w", w), m, list(id_cols), list(order_by or id_cols), seed, tag, source)


def _out(best: DataFrame, id_cols: list[str]) -> DataFrame:
    return best.select("slot", *[F.col(f"item.{c}").alias(c) for c in id_cols])


def _race(df, m, id_cols, order, seed, tag, source):
    each = df.select(*id_cols, "__w", F.explode(F.sequence(F.lit(1), F.lit(m))).alias("slot"))
    e = -F.ln(keyed_uniform([*id_cols, "slot"], seed=seed, tag=tag, source=source)) / F.col("__w")
    return _out(each.select("slot", F.struct(*id_cols).alias("item"), e.alias("e")).groupBy("slot").agg(F.min_by("item", F.struct("e", "item")).alias("item")), id_cols)


def _race_jump(df, m, id_cols, order, seed, tag, source):
    kinds = ",".join(f"`{c}`:{df.schema[c].dataType.simpleString()}" for c in id_cols)

    def keep(batches):
        races, held = SlotRaces(m, keyed_rng(seed, TaskContext.get().partitionId())), None
        for batch in batches:
            if not batch.num_rows:
                continue
            base = races.seen
            races.offer(batch.column(1).to_numpy())
            new = np.flatnonzero(races.item >= base)  # slots that this batch won; only their rows are kept
            rows = batch.column(0).take(pa.array(races.item[new] - base))
            if held is None:
                held = np.empty(m, object)
            held[new] = rows.to_pylist()
            struct = rows.type
        if held is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(1, m + 1, dtype=np.int32)), pa.array(held.tolist(), struct), pa.array(races.time)], ["slot", "item", "e"])

    best = df.select(F.struct(*id_cols).alias("item"), "__w").mapInArrow(keep, f"slot int, item struct<{kinds}>, e double")
    return _out(best.groupBy("slot").agg(F.min_by("item", F.struct("e", "item")).alias("item")), id_cols)


def _proportional(df, m, id_cols, order, seed, tag, source):
    steps = running(df.select("__w", *dict.fromkeys([*id_cols, *[c for c in order if isinstance(c, str)]])), order, {"__run": F.col("__w")}, number="__k")
    each = steps.select(*id_cols, "__w", "__run", "__k", F.explode(F.sequence(F.lit(1), F.lit(m))).alias("slot"))
    taken = each.where(keyed_uniform([*id_cols, "slot"], seed=seed, tag=tag, source=source) * F.col("__run") < F.col("__w"))
    return _out(taken.groupBy("slot").agg(F.max_by(F.struct(*id_cols), "__k").alias("item")), id_cols)


def _sums(df, id_cols, order):
    """Items with the ends of their share of the running sum: neighbours meet at the very same number."""
    return running(df.select("__w", *dict.fromkeys([*id_cols, *[c for c in order if isinstance(c, str)]])), order, {"__run": F.col("__w")}, lower=True)


def _points(steps: DataFrame, points: np.ndarray, id_cols: list[str], *, closed: str) -> DataFrame:
    """(slot, ids) of the item whose share of the running sum holds each point: m points, found by bisection within a task.

    ``closed`` says which end belongs to a share.  Shares cover (0, total] or [0, total) without gaps, so each point has one item.
    """
    shared = steps.sparkSession.sparkContext.broadcast((np.sort(points), np.argsort(points, kind="stable").astype(np.int32) + 1))  # m numbers
    side = "right" if closed == "upper" else "left"

    def search(batches):
        at, slot = shared.value
        for batch in batches:
            lo, hi = batch.column("__run_lower").to_numpy(), batch.column("__run").to_numpy()
            first, last = np.searchsorted(at, lo, side=side), np.searchsorted(at, hi, side=side)
            row = np.repeat(np.arange(len(hi)), last - first)
            if len(row):
                which = np.arange(len(row)) + np.repeat(first - np.cumsum(last - first) + (last - first), last - first)
                yield pa.RecordBatch.from_arrays([pa.array(slot[which]), *[batch.column(c).take(pa.array(row)) for c in id_cols]], ["slot", *id_cols])

    kinds = ", ".join(f"`{c}` {steps.schema[c].dataType.simpleString()}" for c in id_cols)
    return steps.select("__run_lower", "__run", *id_cols).mapInArrow(search, f"slot int, {kinds}")


def slot_uniform(j: int, seed: int, tag: str) -> float:
    return (int(hashlib.md5(f"{seed}|{tag}|{j}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52


def slot_uniforms(m: int, seed: int, tag: str) -> list[float]:
    """The keyed uniforms of slots alone, as the md5 source gives them."""
    return [slot_uniform(j, seed, tag) for j in range(1, m + 1)]


def _ends(steps: DataFrame) -> tuple[float, float] | None:
    """The first and the last running sum."""
    first = steps.agg(F.min("__run"), F.max("__run")).first()
    return None if first[0] is None else (float(first[0]), float(first[1]))


def _none(df, id_cols):
    return df.select(F.lit(1).alias("slot"), *id_cols).limit(0)


def _lookup(df, m, id_cols, order, seed, tag, source):
    steps = _sums(df, id_cols, order)
    ends = _ends(steps)
    if ends is None:
        return _none(df, id_cols)
    # a product may round up to the total, which no share holds
    points = np.minimum(np.array(slot_uniforms(m, seed, tag)) * ends[1], np.nextafter(ends[1], 0))
    return _points(steps, points, id_cols, closed="lower")


def jump_points(m: int, first: float, total: float, rng: np.random.Generator) -> np.ndarray:
    """The last point of each slot's chain of jumps: first, then each the one before over a uniform, up to total.

    A chain has a point in a share (lo, hi] with chance (hi - lo) / hi, whatever came before it: the chance with which the
    single-slot sampler accepts that item.  So the item of the last point is the holder.  About log(total / first) rounds.
    """
    held = np.full(m, first)
    at, live = held.copy(), np.arange(m)
    while len(live):
        at[live] /= (rng.integers(0, 2**52, len(live)) + 0.5) / 2**52
        live = live[at[live] <= total]
        held[live] = at[live]
    return held


def _proportional_jump(df, m, id_cols, order, seed, tag, source):
    steps = _sums(df, id_cols, order)
    ends = _ends(steps)
    if ends is None:
        return _none(df, id_cols)
    return _points(steps, jump_points(m, *ends, keyed_rng(seed, zlib.crc32(tag.encode()))), id_cols, closed="upper")


def single_slot_jump(df: DataFrame, *, weight: Column | str, id_cols: Sequence[str], order_by: Sequence[Column | str] | None = None, seed: int = 0, tag: str = "jump", on_bad_weight: str = "error") -> DataFrame:
    """(ids): the single-slot inclusion-role sampler with jumps, from keyed uniforms; the r-th jump divides by the r-th."""
    good, w = positive_weight(df, weight, on_bad_weight=on_bad_weight)
    ids = list(id_cols)
    steps = _sums(good.withColumn("__w", w), ids, list(order_by or ids))
    ends = _ends(steps)
    if ends is None:
        return df.select(*ids).limit(0)
    at, r = ends[0], 1
    while (more := at / slot_uniform(r, seed, tag)) <= ends[1]:
        at, r = more, r + 1
    return steps.where((F.col("__run_lower") < F.lit(at)) & (F.lit(at) <= F.col("__run"))).select(*ids)
