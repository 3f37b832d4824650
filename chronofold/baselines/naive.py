"""Fan-outs that break a rule.  Each gives wrong answers; tests hold that it does."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO
from ..functions.predicates import predicate
from ..operators.canonical import coalesce_intervals
from ..operators.cohort import ranked_timeline, shard_of
from ..operators.same_base import count_deltas, duration_partials, predicate_window, prefix_steps
from ..sources.history import restrict_window
from ..sources.layout import ChunkGrid
from ..spec import QueryWindow


def start_chunk_only(history: DataFrame, grid: ChunkGrid, window: QueryWindow) -> DataFrame:
    """Each row in the chunk of its start alone, cut to that chunk: what began earlier is lost."""
    rows = history.withColumn("chunk", grid.of(F.col(FROM)))
    rows = rows.withColumn(TO, F.least(F.col(TO), grid.start(F.col("chunk") + 1)))
    return restrict_window(rows, window)


def whole_rows_by_start(history: DataFrame, grid: ChunkGrid, window: QueryWindow) -> DataFrame:
    """Each row, not cut, in the chunk of its start, as far as that touches the window."""
    first, last = grid.chunks_for(window)
    return history.withColumn("chunk", grid.of(F.col(FROM))).where(F.col("chunk").between(first, last))


def mean_of_means(seg: DataFrame, x: str, group: Sequence[str] = ()) -> DataFrame:
    """Each chunk's average, then their average."""
    per_chunk = duration_partials(seg, x, group, by=["chunk"]).withColumn("twa", F.col("weighted_sum").cast("double") / F.col("duration_us"))
    return per_chunk.groupBy(*group).agg(F.avg("twa").alias("twa"))


def threshold_per_shard(seg: DataFrame, keys: Sequence[str], phi, group: Sequence[str], c: int, shards: int) -> DataFrame:
    """The threshold on each shard's count."""
    dealt = seg.withColumn("shard", F.pmod(F.xxhash64(*keys), F.lit(shards)).cast("int"))
    steps = prefix_steps(count_deltas(dealt, phi, group, by=["shard"]), ["shard", *group])
    return coalesce_intervals(steps.where(F.col("active") > c).select(*group, FROM, TO).distinct(), group)


def gate_per_chunk(seg: DataFrame, keys: Sequence[str], phi, evidence) -> DataFrame:
    """The gate within each chunk."""
    kept = predicate_window(seg, [*keys, "chunk"], phi)
    shown = seg.where(predicate(evidence)).select(*keys, "chunk").distinct()
    return coalesce_intervals(kept.join(shown, [*keys, "chunk"], "left_semi").select(*keys, FROM, TO), keys)


def better_without_cover(seg: DataFrame, key: str, reference, x: str) -> DataFrame:
    """Added endpoints without the reference's own presence: stretches of zero are lost."""
    from ..operators.cohort import count_better_than

    return count_better_than(seg, key, reference, x).where("better > 0")


def ranked_per_shard(seg: DataFrame, key: str, x: str, k: int, shards: int) -> DataFrame:
    """Each shard's ranks as they are, not ranked again."""
    parts = seg.withColumn("shard", shard_of(key, shards))
    return ranked_timeline(parts, key, x, k, family=["shard"]).drop("shard")
