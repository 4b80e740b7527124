"""Keyed reservoirs in a stream's own state: one a stratum, changed reservoirs come out after each batch.

State is m entries a stratum however long the stream runs; the global reservoir is a merge of hashed strata.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from wsample.functions.randomness import keyed_uniform
from wsample.functions.times import instant
from wsample.samplers import ProportionalSampler, RaceJumpSampler, RaceSampler, keyed_rng

#: Layout of the state; a checkpoint of another one is refused.
VERSION = 1


def held(state):
    """The state's values, if any; of this layout."""
    old = state.get if state.exists else None
    if old and old[0] != VERSION:
        raise ValueError(f"the state has layout {old[0]}, not {VERSION}")
    return old


def arrived(frames: Iterator[pd.DataFrame]) -> pd.DataFrame:
    """A batch's rows by arrival, then id, each id once."""
    return pd.concat(list(frames)).sort_values(["arrival", "id"], kind="stable").drop_duplicates("id")


def expired(state, ttl_ms: int | None) -> bool:
    """Whether a stratum has had no rows for so long that its state goes; else the time starts anew."""
    if state.hasTimedOut:
        state.remove()
        return True
    if ttl_ms is not None:
        state.setTimeoutDuration(ttl_ms)
    return False


def _race_step(kind, m: int, seed: int, ttl_ms: int | None):
    def step(key, frames: Iterator[pd.DataFrame], state):
        if expired(state, ttl_ms):
            return
        old = held(state)
        sampler = kind.from_state({"m": m, "seen": old[1], "entries": list(zip(old[2], old[3], old[4], strict=True))}) if old else kind(m)
        if kind is RaceJumpSampler:
            sampler.rng = keyed_rng(seed, hash_of(key[0]), sampler.seen)
            sampler.skip = old[5] if old and old[5] >= 0 else None
        rows = arrived(frames)
        known = {e.item for e in sampler.snapshot()}
        rows = rows[~rows["id"].isin(known)]
        sampler.offer(rows["id"].tolist(), rows["w"].to_numpy(), None if kind is RaceJumpSampler else rows["u"].to_numpy())
        kept = sampler.snapshot()
        skip = getattr(sampler, "skip", None)
        state.update((VERSION, sampler.seen, [int(e.item) for e in kept], [e.weight for e in kept], [e.key for e in kept], -1.0 if skip is None else float(skip)))
        yield pd.DataFrame({"stratum": [str(key[0])] * len(kept), "id": [int(e.item) for e in kept], "position": np.arange(1, len(kept) + 1, dtype=np.int32), "seen": [sampler.seen] * len(kept)})

    return step


def _proportional_step(m: int, seed: int, ttl_ms: int | None):
    def step(key, frames: Iterator[pd.DataFrame], state):
        if expired(state, ttl_ms):
            return
        old = held(state)
        if old:
            sampler = ProportionalSampler.from_state({"m": m, "seen": old[1], "slots": list(zip(old[2], old[3], strict=True)), "total": old[4], "pinned": old[5], "pins": [(old[3][s], s) for s in old[6]]})
        else:
            sampler = ProportionalSampler(m)
        sampler.rng = keyed_rng(seed, hash_of(key[0]), sampler.seen)
        rows = arrived(frames)
        sampler.offer(rows["id"].tolist(), rows["w"].to_numpy())
        s = sampler.to_state()
        state.update((VERSION, s["seen"], [int(i) for i, _ in s["slots"]], [w for _, w in s["slots"]], s["total"], s["pinned"], [slot for _, slot in s["pins"]]))
        yield pd.DataFrame({"stratum": [str(key[0])] * len(s["slots"]), "id": [int(i) for i, _ in s["slots"]], "position": np.arange(1, len(s["slots"]) + 1, dtype=np.int32), "seen": [s["seen"]] * len(s["slots"])})

    return step


def hash_of(key) -> int:
    import zlib

    return zlib.crc32(str(key).encode())


def keyed_reservoirs(stream: DataFrame, m: int, *, stratum: str, weight: str, id_col: str, arrival: str, role: str = "draw", jump: bool = False, seed: int = 0, tag: str = "race", source: str = "xxhash", ttl_ms: int | None = None) -> DataFrame:
    """(stratum, id, position, seen) of every reservoir that a batch changed; ids are longs, weights positive.

    A row that comes twice in a batch counts once.  Over batches the race without jumps knows the items it holds, and others
    lose again; jumps and the inclusion role need ``dropDuplicatesWithinWatermark`` before.  With ``ttl_ms`` a stratum without
    rows for so long starts anew; that is for queries that run on, as one that ends with its source would wait for the timeouts.
    """
    rows = stream.select(F.col(stratum).cast("string").alias("stratum"), F.col(id_col).cast("long").alias("id"), F.col(weight).cast("double").alias("w"), F.col(arrival).alias("arrival"), keyed_uniform([id_col], seed=seed, tag=tag, source=source).alias("u"))
    if role == "draw":
        step, kept = _race_step(RaceJumpSampler if jump else RaceSampler, m, seed, ttl_ms), "version int, seen long, items array<long>, weights array<double>, keys array<double>, skip double"
    elif role == "inclusion":
        step, kept = _proportional_step(m, seed, ttl_ms), "version int, seen long, items array<long>, weights array<double>, total double, pinned double, pins array<int>"
    else:
        raise ValueError(f"unknown role: {role!r}")
    return rows.groupBy("stratum").applyInPandasWithState(step, "stratum string, id long, position int, seen long", kept, "update", GroupStateTimeout.NoTimeout if ttl_ms is None else GroupStateTimeout.ProcessingTimeTimeout)


def _window_step(m: int, end_after_us: int):
    def step(key, frames: Iterator[pd.DataFrame], state):
        old = held(state)
        sampler = RaceSampler.from_state({"m": m, "seen": old[1], "entries": list(zip(old[2], old[3], old[4], strict=True))}) if old else RaceSampler(m)
        closed = state.hasTimedOut
        if closed:
            state.remove()
        else:
            end = (int(key[0]) + end_after_us) // 1000
            if end <= state.getCurrentWatermarkMs():
                return  # rows of a window that is closed
            rows = arrived(frames)
            rows = rows[~rows["id"].isin({e.item for e in sampler.snapshot()})]
            sampler.offer(rows["id"].tolist(), rows["w"].to_numpy(), rows["u"].to_numpy())
            kept = sampler.snapshot()
            state.update((VERSION, sampler.seen, [int(e.item) for e in kept], [e.weight for e in kept], [e.key for e in kept]))
            state.setTimeoutTimestamp(end)
        kept = sampler.snapshot()
        yield pd.DataFrame({"window_start": [int(key[0])] * len(kept), "id": [int(e.item) for e in kept], "position": np.arange(1, len(kept) + 1, dtype=np.int32), "closed": [closed] * len(kept)})

    return step


def window_reservoirs(stream: DataFrame, m: int, *, weight: str, id_col: str, time: str, width: str, width_us: int, late: str = "1 hour", slide: str | None = None, seed: int = 0, tag: str = "race", source: str = "xxhash") -> DataFrame:
    """(window_start, id, position, closed): a race of m for every window, whenever a batch changes it and once more when it closes.

    A window closes when the watermark passes its end; its state goes then, and rows that come later are dropped.  ``width_us``
    is the width in microseconds; with ``slide`` windows overlap.
    """
    at = stream.withColumn("__at", instant(time)).withWatermark("__at", late)
    rows = at.select(F.window("__at", width, slide or width).alias("w"), "__at", F.col(id_col).cast("long").alias("id"), F.col(weight).cast("double").alias("w_"), F.col(time).alias("arrival"), keyed_uniform([id_col], seed=seed, tag=tag, source=source).alias("u"))
    rows = rows.select(F.unix_micros("w.start").alias("window_start"), "__at", "id", F.col("w_").alias("w"), "arrival", "u")
    kept = "version int, seen long, items array<long>, weights array<double>, keys array<double>"
    return rows.groupBy("window_start").applyInPandasWithState(_window_step(m, width_us), "window_start long, id long, position int, closed boolean", kept, "update", GroupStateTimeout.EventTimeTimeout)
