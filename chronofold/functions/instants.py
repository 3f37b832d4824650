"""Instants as columns: TIMESTAMP_NTZ (or DATE, read as its midnight) and integer axes alike."""

from __future__ import annotations

import datetime as dt

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

FROM, TO = "valid_from", "valid_to"
EPOCH = dt.datetime(1970, 1, 1)


def instant(value: dt.datetime | int) -> Column:
    """A literal instant."""
    if isinstance(value, int):
        return F.lit(value).cast("long")
    return F.to_timestamp_ntz(F.lit(value.isoformat(sep=" ", timespec="microseconds")))


def micros(at: Column) -> Column:
    """Microseconds since 1970 of a TIMESTAMP_NTZ column."""
    return F.timestamp_diff("MICROSECOND", instant(EPOCH), at)


def from_micros(n: Column) -> Column:
    return F.timestamp_add("MICROSECOND", n, instant(EPOCH))


def to_axis(value: dt.datetime | int) -> int:
    """The driver's counterpart of ``micros``."""
    return value if isinstance(value, int) else (value - EPOCH) // dt.timedelta(microseconds=1)


def on_axis(rows: DataFrame, at: str) -> Column:
    """An instant column as a number: microseconds since 1970, or itself on an integer axis."""
    return F.col(at).cast("long") if isinstance(rows.schema[at].dataType, T.IntegralType) else micros(F.col(at))


def length(start: Column, end: Column, integer: bool = False) -> Column:
    """Length of [start, end): microseconds, or steps of an integer axis."""
    return (end - start).cast("long") if integer else F.timestamp_diff("MICROSECOND", start, end)
