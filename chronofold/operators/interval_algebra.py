"""Union, intersection, difference and complement of two interval sets per key, by one sweep over coverage counts."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO
from .canonical import coalesce_intervals


def _covered(a: DataFrame, b: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Stretches between cuts of a key, with how often each side covers them."""

    def ends(rows: DataFrame, left: int, right: int) -> DataFrame:
        pair = F.array(*(F.struct(F.col(c).alias("at"), F.lit(s * left).cast("long").alias("l"), F.lit(s * right).cast("long").alias("r")) for c, s in ((FROM, 1), (TO, -1))))
        return rows.select(*keys, F.explode(pair).alias("e")).select(*keys, "e.*")

    events = ends(a, 1, 0).unionByName(ends(b, 0, 1)).groupBy(*keys, "at").agg(F.sum("l").alias("l"), F.sum("r").alias("r"))
    by = Window.partitionBy(*keys).orderBy("at")
    far = by.rowsBetween(Window.unboundedPreceding, 0)
    return events.select(*keys, F.col("at").alias(FROM), F.lead("at").over(by).alias(TO), F.sum("l").over(far).alias("l"), F.sum("r").over(far).alias("r")).where(F.col(TO).isNotNull())


def union(a: DataFrame, b: DataFrame, keys: Sequence[str]) -> DataFrame:
    return coalesce_intervals(_covered(a, b, keys).where("l > 0 OR r > 0"), keys)


def intersect(a: DataFrame, b: DataFrame, keys: Sequence[str]) -> DataFrame:
    return coalesce_intervals(_covered(a, b, keys).where("l > 0 AND r > 0"), keys)


def subtract(a: DataFrame, b: DataFrame, keys: Sequence[str]) -> DataFrame:
    return coalesce_intervals(_covered(a, b, keys).where("l > 0 AND r = 0"), keys)


def complement(a: DataFrame, known: DataFrame, keys: Sequence[str], low: Column, high: Column) -> DataFrame:
    """What each known key leaves free of [low, high)."""
    whole = known.select(*keys).distinct().withColumns({FROM: low, TO: high})
    return subtract(whole, a, keys)
