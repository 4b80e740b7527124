"""Timestamps without time zones, whatever the session's."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def micros(time: Column | str) -> Column:
    """Microseconds since 1970 of a timestamp, its wall clock taken as it stands."""
    t = (F.col(time) if isinstance(time, str) else time).cast("timestamp_ntz")
    return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), t)


def instant(time: Column | str) -> Column:
    """A timestamp for watermarks: the wall clock read as UTC."""
    return F.timestamp_micros(micros(time))
