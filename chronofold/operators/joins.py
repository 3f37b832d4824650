"""Joins on time for users of histories; none of them is an N-way temporal join."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO


def asof_join(left: DataFrame, right: DataFrame, on: Sequence[str], left_at: str, right_at: str, columns: Sequence[str], tie: Sequence[str] = ()) -> DataFrame:
    """Each left row with ``columns`` of the latest right row at or before it; one exchange by ``on``, no range join."""
    l = left.withColumn("_l", F.struct(*left.columns)).select(*on, F.col(left_at).alias("_at"), F.lit(1).alias("_side"), "_l", *(F.lit(None).cast(right.schema[t].dataType).alias(f"_t{i}") for i, t in enumerate(tie)))
    r = right.select(*on, F.col(right_at).alias("_at"), F.lit(0).alias("_side"), F.struct(*columns).alias("_r"), *(F.col(t).alias(f"_t{i}") for i, t in enumerate(tie)))
    both = l.unionByName(r, allowMissingColumns=True)
    by = Window.partitionBy(*on).orderBy("_at", "_side", *(f"_t{i}" for i in range(len(tie)))).rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("_r", F.last("_r", ignorenulls=True).over(by)).where("_side = 1")
    return found.select("_l.*", *(F.col(f"_r.{c}").alias(c) for c in columns))


def overlap_join(a: DataFrame, b: DataFrame, chunk_of, on: Sequence[str] = ()) -> DataFrame:
    """Pairs of rows that overlap, each once, with the overlap as ``valid_from`` and ``valid_to``; sides keep their columns under
    ``a`` and ``b``.  Rows meet in each chunk that they share; the chunk in which the overlap begins owns the pair.

    ``chunk_of``: maps an instant column to a whole number, ascending.
    """

    def spread(rows: DataFrame, name: str) -> DataFrame:
        first, last = chunk_of(F.col(FROM)), chunk_of(F.col(TO))
        return rows.select(*on, F.struct(*rows.columns).alias(name), F.explode(F.sequence(first, last)).alias("_c"))

    met = spread(a, "a").join(spread(b, "b"), [*on, "_c"])
    f, t = F.greatest(f"a.{FROM}", f"b.{FROM}"), F.least(f"a.{TO}", f"b.{TO}")
    met = met.withColumns({FROM: f, TO: t}).where(F.col(FROM) < F.col(TO))
    return met.where(chunk_of(F.col(FROM)) == F.col("_c")).select(*on, "a", "b", FROM, TO)


def range_join(a: DataFrame, b: DataFrame, left: Column, right: Column, width: int, on: Sequence[str] = ()) -> DataFrame:
    """Pairs whose whole numbers differ by at most ``width``: bins of that width, and each right row in its own and both
    neighbours."""
    x = a.select(*on, F.struct(*a.columns).alias("a"), left.cast("long").alias("_v")).withColumn("_bin", F.floor(F.col("_v") / width).cast("long"))
    y = b.select(*on, F.struct(*b.columns).alias("b"), right.cast("long").alias("_w"))
    own = F.floor(F.col("_w") / width).cast("long")
    y = y.withColumn("_bin", F.explode(F.array(own - 1, own, own + 1)))
    return x.join(y, [*on, "_bin"]).where(F.abs(F.col("_v") - F.col("_w")) <= width).select(*on, "a", "b")


def point_in_interval(points: DataFrame, history: DataFrame, at: str, chunk_of, on: Sequence[str] = ()) -> DataFrame:
    """Each point with the rows that hold at it, by chunk and containment."""
    p = points.withColumn("_c", chunk_of(F.col(at)))
    h = history.withColumn("_c", F.explode(F.sequence(chunk_of(F.col(FROM)), chunk_of(F.col(TO)))))
    return p.join(h, [*on, "_c"]).where((F.col(FROM) <= F.col(at)) & (F.col(at) < F.col(TO))).drop("_c")
