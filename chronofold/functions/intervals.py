"""Predicates and helpers on half-open intervals [start, end)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def overlaps(a_from: Column, a_to: Column, b_from: Column, b_to: Column) -> Column:
    return (a_from < b_to) & (b_from < a_to)


def contains_instant(start: Column, end: Column, at: Column) -> Column:
    """An open end (null) lasts."""
    return (start <= at) & (end.isNull() | (at < end))


def before(a_from: Column, a_to: Column, b_from: Column, b_to: Column) -> Column:
    return a_to < b_from


def meets(a_from: Column, a_to: Column, b_from: Column, b_to: Column) -> Column:
    return a_to == b_from


def during(a_from: Column, a_to: Column, b_from: Column, b_to: Column) -> Column:
    return (a_from > b_from) & (a_to < b_to)


def starts(a_from: Column, a_to: Column, b_from: Column, b_to: Column) -> Column:
    return (a_from == b_from) & (a_to < b_to)


def finishes(a_from: Column, a_to: Column, b_from: Column, b_to: Column) -> Column:
    return (a_to == b_to) & (a_from > b_from)


def equals_iv(a_from: Column, a_to: Column, b_from: Column, b_to: Column) -> Column:
    return (a_from == b_from) & (a_to == b_to)


def clip_from(start: Column, low: Column) -> Column:
    return F.greatest(start, low)


def clip_to(end: Column, high: Column) -> Column:
    """A null end is open."""
    return F.least(end, high)


def midpoint(start: Column, end: Column) -> Column:
    return F.timestamp_add("MICROSECOND", F.floor(F.timestamp_diff("MICROSECOND", start, end) / 2), start)
