"""Connected components of a graph held as an edge table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import finished, spool, spread_join, temporary


def _state(edges: DataFrame) -> tuple[int, int]:
    row = edges.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("low", "high") % (1 << 40)).alias("h")).first()
    return int(row.n), int(row.h or 0)


def component_roots(edges: DataFrame, low: str, high: str) -> DataFrame:
    """(node, root) for every node of an edge whose component's smallest node is another; long nodes.

    Large-star and small-star steps by turns: each node hands its larger neighbours, then its smaller ones, to its least
    neighbour, until every edge leads to its component's least node.  A step keeps at most as many distinct edges as it gets,
    the minima are pre-aggregated, a hub's edges are dealt over many tasks, and each step's edges go to the shared folder, so
    neither a hub nor a long chain needs more than one task's share.
    """
    with temporary(edges.sparkSession):
        edges = edges.select(F.least(low, high).alias("low"), F.greatest(low, high).alias("high")).where("low < high").distinct()
        edges = spool(edges)
        state = _state(edges)
        while state[0]:
            both = edges.select(F.col("low").alias("u"), F.col("high").alias("v")).unionByName(edges.select(F.col("high").alias("u"), F.col("low").alias("v")))
            least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
            large = spool(spread_join(both.where("v > u"), least, ["u"], "v").select(F.col("m").alias("low"), F.col("v").alias("high")).distinct())
            parent = large.groupBy("high").agg(F.min("low").alias("m"))
            handed = spread_join(large, parent, ["high"], "low").select(F.explode(F.array(F.struct(F.col("m").alias("low"), F.col("low").alias("high")), F.struct(F.col("m").alias("low"), F.col("high").alias("high")))).alias("e"))
            edges = spool(handed.select("e.low", "e.high").where("low < high").distinct())
            before, state = state, _state(edges)
            if state == before:
                break
        return finished(edges.select(F.col("high").alias("node"), F.col("low").alias("root")))
