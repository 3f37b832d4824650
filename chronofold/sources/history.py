"""Interval histories: built from change logs and snapshots, checked, cut to a window, looked up."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO, instant
from ..functions.intervals import contains_instant
from ..spec import HistorySpec, Instant, QueryWindow


def from_change_log(changes: DataFrame, keys: Sequence[str], at: str, payload: Sequence[str], tie: Sequence[str] = (), horizon: Instant | None = None, compact: bool = False, op: str | None = None) -> DataFrame:
    """Rows [this change, next change of the key); the last one lasts to the horizon, or stays open.

    ``tie`` orders changes of one instant, the last of which counts.  ``op``: a column that says delete where the key ends.
    ``compact`` joins neighbours of equal payload.  Changes with a null key or instant are no changes.  One shuffle by key.
    """
    known = changes.where(" AND ".join(f"`{c}` IS NOT NULL" for c in [*keys, at]))
    by_key = Window.partitionBy(*keys).orderBy(at, *tie)
    rows = known.withColumn(TO, F.lead(at).over(by_key)).withColumnRenamed(at, FROM)
    if op is not None:
        rows = rows.where(F.coalesce(F.lower(F.col(op)) != "delete", F.lit(True)))
    if horizon is not None:
        rows = rows.withColumn(TO, F.coalesce(TO, instant(horizon)))
    rows = rows.where(F.col(TO).isNull() | (F.col(FROM) < F.col(TO))).select(*keys, *payload, FROM, TO)
    if compact:
        from ..operators.canonical import coalesce_intervals

        rows = coalesce_intervals(rows, keys, payload)
    return rows


def from_snapshots(rows: DataFrame, keys: Sequence[str], at: str, payload: Sequence[str], step: Column) -> DataFrame:
    """History of (entity, instant) rows taken every ``step`` (an interval, or a number on an integer axis): each holds for a step,
    neighbours of equal payload are one row."""
    from ..operators.canonical import coalesce_intervals

    timed = rows.select(*keys, *payload, F.col(at).alias(FROM), (F.col(at) + step).alias(TO))
    return coalesce_intervals(timed, keys, payload)


def fill_full_state(changes: DataFrame, keys: Sequence[str], at: str, columns: Sequence[str], tie: Sequence[str] = (), changed: str | None = None) -> DataFrame:
    """Full-state rows of a log that shows only changed columns.  ``changed``: an array of the names each row changes, so that a
    change to null differs from no change; without it a null is no change."""
    frame = Window.partitionBy(*keys).orderBy(at, *tie).rowsBetween(Window.unboundedPreceding, 0)
    filled = []
    for c in columns:
        if changed is None:
            filled.append(F.last(c, ignorenulls=True).over(frame).alias(c))
        else:
            set_here = F.when(F.array_contains(changed, c), F.struct(F.col(c).alias("v")))
            filled.append(F.last(set_here, ignorenulls=True).over(frame)["v"].alias(c))
    rest = [c for c in changes.columns if c not in columns]
    return changes.select(*rest, *filled)


def validate_history(history: DataFrame, spec: HistorySpec) -> DataFrame:
    """Violations: (keys, valid_from, valid_to, problem) for null keys, empty intervals, and overlaps within a key."""
    over = Window.partitionBy(*spec.keys).orderBy(FROM, TO).rowsBetween(Window.unboundedPreceding, -1)
    open_end = F.coalesce(F.col(TO), F.max(TO).over(Window.partitionBy(*spec.keys)), F.col(FROM))
    seen = history.withColumn("_end", F.when(F.col(TO).isNull(), F.greatest(open_end, F.col(FROM))).otherwise(F.col(TO)))
    seen = seen.withColumn("_before", F.max("_end").over(over)).withColumn("_open", F.max(F.col(TO).isNull()).over(over))
    missing = F.lit(False)
    for k in spec.keys:
        missing = missing | F.col(k).isNull()
    problem = F.when(missing, "null key").when(F.col(FROM).isNull() | (F.col(FROM) >= F.col(TO)), "empty interval")
    problem = problem.when((F.col("_before") > F.col(FROM)) | F.coalesce("_open", F.lit(False)), "overlap")
    return seen.select(*spec.keys, FROM, TO, problem.alias("problem")).where("problem IS NOT NULL")


def state_at(history: DataFrame, at: Instant) -> DataFrame:
    """The one row of each key that holds at an instant."""
    return history.where(contains_instant(F.col(FROM), F.col(TO), instant(at)))


def restrict_window(history: DataFrame, window: QueryWindow) -> DataFrame:
    """Rows that overlap the window, clipped to it; an open end reaches the window's."""
    rows = history.where((F.col(FROM) < window.high) & (F.col(TO).isNull() | (F.col(TO) > window.low)))
    clipped = rows.withColumns({FROM: F.greatest(F.col(FROM), window.low), TO: F.least(F.col(TO), window.high)})
    return clipped.where(F.col(FROM) < F.col(TO))


def to_snapshots(history: DataFrame, step: Column, at: str = "at") -> DataFrame:
    """One row per key and step from each row's start; for checks on small inputs, as it grows with time."""
    rows = history.withColumn(at, F.explode(F.sequence(F.col(FROM), F.col(TO), step)))
    return rows.where(F.col(at) < F.col(TO)).drop(FROM, TO)


def with_dims(history: DataFrame, dimension: DataFrame, on: str | Sequence[str]) -> DataFrame:
    """Join attributes that don't vary in time.  Spark broadcasts a dimension that is small enough by its own threshold."""
    return history.join(dimension, on, "left")


def dedupe(rows: DataFrame, keys: Sequence[str], order: Sequence) -> DataFrame:
    """The first row of each key in a declared order."""
    return rows.withColumn("_n", F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).where("_n = 1").drop("_n")
