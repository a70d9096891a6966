"""Small column functions: time as numbers, and values that are computed once."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def micros(t: str | Column) -> Column:
    """Microseconds from 1970 to a timestamp's local time, with or without a zone."""
    t = F.col(t) if isinstance(t, str) else t
    return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), t)


def let(value: Column, use) -> Column:
    """``use`` of a value that is computed once: bound to a lambda's variable, which the optimiser doesn't copy."""
    return F.get(F.transform(F.array(value), use), 0)
