"""Operators whose result follows from one row at a time.

Segments are rows (keys, payload, valid_from, valid_to) cut to the query's window, from a layout also to a ``chunk``.  Every
operator gives the same canonical result whatever the chunks are.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO, length
from ..functions.predicates import Pred, predicate
from .canonical import coalesce_intervals

Phi = Pred | Column | str


def chunked(rows: DataFrame) -> DataFrame:
    """Rows with a column chunk; a history that was never cut is one chunk."""
    return rows if "chunk" in rows.columns else rows.withColumn("chunk", F.lit(0))


# Predicate windows and booleans of predicates.


def predicate_window(seg: DataFrame, keys: Sequence[str], phi: Phi, payload: Sequence[str] = (), canon: bool = True) -> DataFrame:
    """Where the predicate holds, with the payload asked for; ``canon=False`` leaves the pieces as they are."""
    kept = seg.where(predicate(phi)).select(*keys, *payload, FROM, TO)
    return coalesce_intervals(kept, keys, payload) if canon else kept


def project_window(seg: DataFrame, keys: Sequence[str], payload: Sequence[str]) -> DataFrame:
    return coalesce_intervals(seg.select(*keys, *payload, FROM, TO), keys, payload)


def boolean_window(seg: DataFrame, keys: Sequence[str], a: Phi, b: Phi, op: str, payload: Sequence[str] = (), canon: bool = True) -> DataFrame:
    """``op``: and, or, minus.  One boolean on one row, no intersection of intervals."""
    x, y = Pred(predicate(a)), Pred(predicate(b))
    whole = {"and": lambda: x & y, "or": lambda: x | y, "minus": lambda: x - y}
    if op not in whole:
        raise ValueError(f"op is and, or, or minus, not {op}")
    return predicate_window(seg, keys, whole[op](), payload, canon)


# Sums weighted by duration.


def duration_partials(seg: DataFrame, x: Column | str | None, group: Mapping[str, Column] | Sequence[str] = (), by: Sequence[str] = (), integer: bool = False, window_start: Column | None = None) -> DataFrame:
    """Additive sums per group, and per ``by`` (a piece): weighted sum (exact decimal), duration, segments, least and greatest x, and
    ``n_intervals``: segments that begin their interval, which doesn't depend on the chunks.

    Rows whose x is null count for nothing; without x each row counts its time alone.  ``window_start`` makes the rows it cuts
    heads of their intervals.
    """
    value = F.lit(1).cast("decimal(18,2)") if x is None else (F.expr(x) if isinstance(x, str) else x).cast("decimal(18,2)")
    named = dict(group) if isinstance(group, Mapping) else {g: F.col(g) for g in group}
    rows = seg.select(*by, *(c.alias(n) for n, c in named.items()), value.alias("_x"), length(F.col(FROM), F.col(TO), integer).alias("_d"), FROM, (F.col("is_head") if "is_head" in seg.columns else F.lit(True)).alias("_head"))
    head = F.col("_head") if window_start is None else F.col("_head") | (F.col(FROM) == window_start)
    rows = rows.where("_x IS NOT NULL")
    sums = [
        F.sum(F.col("_x") * F.col("_d").cast("decimal(20,0)")).cast("decimal(38,2)").alias("weighted_sum"), F.sum("_d").alias("duration_us"), F.count(F.lit(1)).alias("n"),
        F.min("_x").alias("x_min"), F.max("_x").alias("x_max"), F.sum(head.cast("long")).alias("n_intervals"),
    ]
    return rows.groupBy(*by, *named).agg(*sums)


def merge_durations(partials: DataFrame, group: Sequence[str]) -> DataFrame:
    """Sums of partials, and least and greatest."""
    return partials.groupBy(*group).agg(
        F.sum("weighted_sum").cast("decimal(38,2)").alias("weighted_sum"), F.sum("duration_us").alias("duration_us"), F.sum("n").alias("n"),
        F.min("x_min").alias("x_min"), F.max("x_max").alias("x_max"), F.sum("n_intervals").alias("n_intervals"),
    )


def finalize_durations(merged: DataFrame, group: Sequence[str], digits: int | None = None) -> DataFrame:
    """The one division."""
    ratio = F.col("weighted_sum").cast("double") / F.col("duration_us")
    ratio = ratio if digits is None else F.round(ratio, digits)
    return merged.select(*group, "weighted_sum", "duration_us", "x_min", "x_max", ratio.alias("twa"))


def duration_aggregate(seg: DataFrame, x: Column | str | None, group: Mapping[str, Column] | Sequence[str] = (), digits: int | None = None, integer: bool = False) -> DataFrame:
    """Partial and final aggregation in one plan: a single exchange, by the group."""
    return finalize_durations(duration_partials(seg, x, group, integer=integer), list(group), digits)


def time_in_state(seg: DataFrame, group: Sequence[str]) -> DataFrame:
    return duration_aggregate(seg, None, group).select(*group, "duration_us")


def time_share(seg: DataFrame, group: Sequence[str], members: int, window_us: int) -> DataFrame:
    """Share of all members' window time that each group has."""
    return time_in_state(seg, group).withColumn("share", F.col("duration_us") / F.lit(float(members) * window_us))


def duration_rollup(seg: DataFrame, x: str, levels: Sequence[str], cube: bool = False, digits: int | None = 6) -> DataFrame:
    """Weighted means on all levels of a rollup (or cube), from the same additive sums; ``level`` tells grouped nulls apart."""
    partials = duration_partials(seg, x, levels)
    grouped = partials.cube(*levels) if cube else partials.rollup(*levels)
    sums = grouped.agg(F.sum("weighted_sum").cast("decimal(38,2)").alias("weighted_sum"), F.sum("duration_us").alias("duration_us"), F.grouping_id().alias("level"))
    ratio = F.col("weighted_sum").cast("double") / F.col("duration_us")
    return sums.withColumn("twa", ratio if digits is None else F.round(ratio, digits))


# Count timelines.


def count_deltas(seg: DataFrame, phi: Phi | None, group: Mapping[str, Column] | Sequence[str] = (), encoding: str = "delta", by: Sequence[str] = ()) -> DataFrame:
    """(by, group, chunk, at, delta) with one row per instant and none of zero.

    ``encoding="step"`` first forms each piece's count steps and states those as deltas; the sums are the same.
    """
    named = dict(group) if isinstance(group, Mapping) else {g: F.col(g) for g in group}
    rows = chunked(seg)
    if phi is not None:
        rows = rows.where(predicate(phi))
    rows = rows.select(*by, *(c.alias(n) for n, c in named.items()), "chunk", FROM, TO)
    ends = F.array(F.struct(F.col(FROM).alias("at"), F.lit(1).cast("long").alias("delta")), F.struct(F.col(TO).alias("at"), F.lit(-1).cast("long").alias("delta")))
    ids = [*by, *named, "chunk"]
    deltas = rows.select(*ids, F.explode(ends).alias("e")).groupBy(*ids, F.col("e.at").alias("at")).agg(F.sum("e.delta").alias("delta")).where("delta <> 0")
    if encoding == "delta":
        return deltas
    if encoding != "step":
        raise ValueError(f"encoding is delta or step, not {encoding}")
    steps = prefix_steps(deltas, [*by, *named])
    again = F.array(F.struct(F.col(FROM).alias("at"), F.col("active").alias("delta")), F.struct(F.col(TO).alias("at"), (-F.col("active")).alias("delta")))
    return steps.select(*ids, F.explode(again).alias("e")).groupBy(*ids, F.col("e.at").alias("at")).agg(F.sum("e.delta").alias("delta")).where("delta <> 0")


def prefix_steps(deltas: DataFrame, group: Sequence[str], value: str = "delta", name: str = "active") -> DataFrame:
    """Running sums between instants, from deltas summed by (group, chunk, at).

    Rows are cut to their chunk, so each chunk's deltas begin and end at zero: no sum is carried from chunk to chunk, and all
    (group, chunk) run side by side.
    """
    by = Window.partitionBy(*group, "chunk").orderBy("at")
    steps = deltas.withColumn(name, F.sum(value).over(by.rowsBetween(Window.unboundedPreceding, 0))).withColumn(TO, F.lead("at").over(by))
    return steps.select(*group, "chunk", F.col("at").alias(FROM), TO, name).where(F.col(TO).isNotNull() & (F.col(name) != 0))


def merge_counts(partials: DataFrame, group: Sequence[str]) -> DataFrame:
    """The full timeline from the deltas of any pieces."""
    summed = partials.groupBy(*group, "chunk", "at").agg(F.sum("delta").alias("delta"))
    return coalesce_intervals(prefix_steps(summed, group), group, ["active"])


def count_timeline(seg: DataFrame, phi: Phi | None, group: Mapping[str, Column] | Sequence[str] = (), encoding: str = "delta", cluster_first: bool = False) -> DataFrame:
    """(group, valid_from, valid_to, active): how many rows hold the predicate, where any does.

    Default: deltas are summed before the exchange, which suits coarse instants that many rows share.  ``cluster_first`` sends the
    rows to their (group, chunk) once and sums there, which suits instants that are all different.
    """
    names = list(group)
    if cluster_first:
        named = dict(group) if isinstance(group, Mapping) else {g: F.col(g) for g in group}
        seg = chunked(seg).withColumns(named) if named else chunked(seg)
        seg = seg.repartition(*names, "chunk")
        group = names
    deltas = count_deltas(seg, phi, group, encoding)
    return coalesce_intervals(prefix_steps(deltas, names), names, ["active"])


def with_zeros(timeline: DataFrame, groups: DataFrame, group: Sequence[str], low: Column, high: Column) -> DataFrame:
    """A timeline that also has the stretches of count zero, for each known group, over [low, high)."""
    from .interval_algebra import complement

    none = complement(timeline.select(*group, FROM, TO), groups, group, low, high).withColumn("active", F.lit(0).cast("long"))
    return timeline.unionByName(none.select(*timeline.columns))


def threshold_windows(timeline: DataFrame, group: Sequence[str], c: int) -> DataFrame:
    """Where the full count exceeds c."""
    return coalesce_intervals(timeline.where(F.col("active") > c), group)


def count_peak(timeline: DataFrame, group: Sequence[str]) -> DataFrame:
    """Greatest count of each group and when it is first reached."""
    top = F.max(F.struct("active", (-F.unix_micros(F.col(FROM).cast("timestamp"))).alias("early"), FROM))
    return timeline.groupBy(*group).agg(top.alias("t")).select(*group, F.col("t.active").alias("active"), F.col(f"t.{FROM}").alias(FROM))


def distinct_keys(seg: DataFrame, keys: Sequence[str], group: Sequence[str], rsd: float | None = None) -> DataFrame:
    """Keys seen per group in the window, exact, or estimated within ``rsd`` for profiling."""
    key = F.struct(*keys)
    return seg.groupBy(*group).agg((F.count_distinct(key) if rsd is None else F.approx_count_distinct(F.xxhash64(*keys), rsd)).alias("n_keys"))
