"""The five kinds of partial results, by the columns that a merge needs."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO

WINDOW, DURATION, DELTA, STEP, ALIGNED = "window", "duration", "count delta", "step", "aligned"

#: Columns beside keys, groups or payload.
COLUMNS = {WINDOW: (FROM, TO), DURATION: ("weighted_sum", "duration_us", "n", "x_min", "x_max"), DELTA: ("chunk", "at", "delta"), STEP: ("chunk", FROM, TO, "active"), ALIGNED: (FROM, TO)}


def broken(partial: DataFrame, kind: str, ids: Sequence[str]) -> DataFrame:
    """Rows against a kind's invariant: overlapping windows of a key, repeated or zero deltas, several sums of a group."""
    lacking = [c for c in (*ids, *COLUMNS[kind]) if c not in partial.columns]
    if lacking:
        raise ValueError(f"a partial of kind {kind} lacks {lacking}")
    if kind == DELTA:
        return partial.groupBy(*ids, "chunk", "at").agg(F.count(F.lit(1)).alias("rows"), F.sum("delta").alias("delta")).where("rows > 1 OR delta = 0")
    if kind == DURATION:
        return partial.groupBy(*ids).count().where("count > 1")
    from pyspark.sql import Window

    earlier = F.max(TO).over(Window.partitionBy(*ids).orderBy(FROM, TO).rowsBetween(Window.unboundedPreceding, -1))
    return partial.withColumn("_before", earlier).where(F.col("_before") > F.col(FROM)).drop("_before")
