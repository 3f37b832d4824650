"""The canonical form: maximal intervals under a stated criterion, and comparison in it."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO


def coalesce_intervals(rows: DataFrame, ids: Sequence[str], on: Sequence[str] = ()) -> DataFrame:
    """Join rows of one id that meet end to start and agree (nulls too) on ``on``; other columns go.

    The islands' grouping keeps the window's partitioning, so there is one exchange, by the ids.  Without ids the rows are one
    group, which is only for results that are small by nature.
    """
    ids, on = list(ids), list(on)
    by_id = Window.partitionBy(*ids).orderBy(FROM, TO)
    same = F.lag(TO).over(by_id) == F.col(FROM)
    for c in on:
        same = same & F.lag(c).over(by_id).eqNullSafe(F.col(c))
    marked = rows.select(*ids, *on, FROM, TO).withColumn("_new", F.when(F.coalesce(same, F.lit(False)), 0).otherwise(1))
    marked = marked.withColumn("_island", F.sum("_new").over(by_id.rowsBetween(Window.unboundedPreceding, 0)))
    values = [F.first(c).alias(c) for c in on]
    return marked.groupBy(*ids, "_island").agg(*values, F.min(FROM).alias(FROM), F.max(TO).alias(TO)).select(*ids, *on, FROM, TO)


def coalesce_pieces(rows: DataFrame, ids: Sequence[str], on: Sequence[str] = ()) -> DataFrame:
    """The same for rows with a column chunk that were cut to chunks, when few ids have long timelines (a rank, a pair): joined
    within (ids, chunk) first, side by side; then only each chunk's first and last stretch, which alone can touch another
    chunk's, meet by id."""
    ids, on = list(ids), list(on)
    inner = coalesce_intervals(rows, [*ids, "chunk"], on)
    of_chunk = Window.partitionBy(*ids, "chunk")
    outer = (F.col(FROM) == F.min(FROM).over(of_chunk)) | (F.col(TO) == F.max(TO).over(of_chunk))
    marked = inner.withColumn("_outer", outer)
    return coalesce_intervals(marked.where("_outer"), ids, on).unionByName(marked.where("NOT _outer").select(*ids, *on, FROM, TO))


def stitch_edges(rows: DataFrame, ids: Sequence[str], on: Sequence[str], edges: DataFrame) -> DataFrame:
    """The same for rows that are canonical within chunks: only rows that touch a chunk edge (a small table of instants ``at``) are
    regrouped, the rest pass by."""
    at_edge = F.broadcast(edges.select("at").distinct())
    touched = rows.join(at_edge, (F.col(FROM) == F.col("at")) | (F.col(TO) == F.col("at")), "left_semi")
    apart = rows.join(at_edge, (F.col(FROM) == F.col("at")) | (F.col(TO) == F.col("at")), "left_anti")
    return coalesce_intervals(touched, ids, on).unionByName(apart.select(*ids, *on, FROM, TO))


def canonical_equal(a: DataFrame, b: DataFrame) -> tuple[int, int]:
    """Rows only in a, and only in b, as multisets; both with the same columns."""
    b = b.select(*a.columns)
    return a.exceptAll(b).count(), b.exceptAll(a).count()


def keys_correct(found: DataFrame, oracle: DataFrame, keys: Sequence[str]) -> tuple[int, int]:
    """(keys whose interval sets agree, keys of either)."""
    oracle = oracle.select(*found.columns)
    wrong = found.exceptAll(oracle).select(*keys).union(oracle.exceptAll(found).select(*keys)).distinct()
    every = found.select(*keys).union(oracle.select(*keys)).distinct()
    n = every.count()
    return n - wrong.count(), n
