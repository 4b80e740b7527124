"""Keyed uniforms: a pure function of (seed, tag, id columns[, slot]).

A retried, speculated or re-partitioned task recomputes the same number, which
``rand()`` does not promise.  Every uniform lies strictly inside (0, 1).
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Uniforms carry 52 bits, so that (h + 0.5) / 2**52 is exact in a double.
SPAN = 2**52


def _parts(seed: int, tag: str, cols: Sequence[Column | str]) -> list[Column]:
    return [F.lit(str(seed)), F.lit(tag), *[F.col(c) if isinstance(c, str) else c for c in cols]]


def keyed_hash(cols: Sequence[Column | str], *, seed: int = 0, tag: str = "race", source: str = "xxhash") -> Column:
    """A 52-bit non-negative long.  ``md5`` has an exact twin in other SQL engines; ``xxhash`` is the fast default."""
    if source == "md5":
        text = F.concat_ws("|", *[p.cast("string") for p in _parts(seed, tag, cols)])
        return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")
    if source == "xxhash":
        return F.shiftrightunsigned(F.xxhash64(*_parts(seed, tag, cols)), 12)
    raise ValueError(f"unknown source of uniforms: {source!r}")


def keyed_uniform(cols: Sequence[Column | str], *, seed: int = 0, tag: str = "race", source: str = "xxhash") -> Column:
    """A double in the open interval (0, 1).  ``rand`` follows partition order and is not stable under retries."""
    if source == "rand":
        return (F.floor(F.rand(seed) * SPAN) + 0.5) / F.lit(float(SPAN))
    return (keyed_hash(cols, seed=seed, tag=tag, source=source) + F.lit(0.5)) / F.lit(float(SPAN))
