"""A change stream as closed intervals.

An interval goes out once its end is at or before the watermark, so nothing is ever taken back.  A change that comes late, but
within the watermark, takes its place among the pending ones of its key; later ones go to a table of rejected rows.
"""

from __future__ import annotations

import datetime as dt
from collections.abc import Iterator, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.instants import FROM, TO
from ..sources.layout import ChunkGrid


def closed_intervals(changes: DataFrame, key: str, at: str, payload: Sequence[str], tie: Sequence[str] = (), delay: str = "2 hours") -> DataFrame:
    """(key, payload, valid_from, valid_to) of every interval that the watermark has passed.  ``at`` is a timestamp column (instants
    of a zone-less column are those of UTC)."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    kinds = {f.name: f.dataType for f in changes.schema.fields}
    columns = [at, *tie, *payload]
    out = T.StructType([T.StructField(key, kinds[key]), *(T.StructField(c, kinds[c]) for c in payload), T.StructField(FROM, T.TimestampType()), T.StructField(TO, T.TimestampType())])
    state = T.StructType([T.StructField("pending", T.BinaryType())])

    def advance(k: tuple, batches: Iterator, held: GroupState) -> Iterator:
        import pickle

        import pandas as pd

        pending: list[tuple] = pickle.loads(held.get[0]) if held.exists else []
        mark = held.getCurrentWatermarkMs()
        for b in batches:
            pending += list(b[columns].itertuples(index=False, name=None))
        pending.sort(key=lambda r: r[: 1 + len(tie)])
        limit = pd.Timestamp(mark, unit="ms") if mark > 0 else pd.Timestamp.min
        rows, keep = [], 0
        for i in range(len(pending) - 1):
            start, end = pending[i][0], pending[i + 1][0]
            if end > limit:
                break
            if start < end:
                rows.append((k[0], *pending[i][1 + len(tie) :], start, end))
            keep = i + 1
        held.update((pickle.dumps(pending[keep:]),))
        if len(pending) - keep > 1:
            held.setTimeoutTimestamp(max(mark + 1, int(pending[keep + 1][0].timestamp() * 1000) + 1))
        yield pd.DataFrame(rows, columns=out.fieldNames())

    marked = changes.withWatermark(at, delay)
    return marked.groupBy(key).applyInPandasWithState(advance, out, state, "append", GroupStateTimeout.EventTimeTimeout)


def sealed_chunks(grid: ChunkGrid, watermark: dt.datetime) -> int:
    """The last chunk that a watermark has passed in full: up to it, chunks hold all that shapes them."""
    return grid.id_of(watermark) - 1


def write_chunks(path: str, grid: ChunkGrid, keys: Sequence[str]):
    """A foreachBatch sink: each batch's clipped rows under their chunk and batch, written over if the batch comes again."""
    from ..sources.layout import clip_to_chunks

    def write(batch: DataFrame, number: int) -> None:
        ntz = batch.withColumns({c: F.col(c).cast("timestamp_ntz") for c in (FROM, TO)})
        rows = clip_to_chunks(ntz, grid, keys).withColumn("batch", F.lit(number))
        rows.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("chunk", "batch").parquet(path)

    return write


def late_rows(changes: DataFrame, at: str, watermark: dt.datetime) -> DataFrame:
    """Changes before a watermark that was already passed, for the table of rejected rows."""
    return changes.where(F.col(at) < F.lit(watermark))


def tumbling_counts(changes: DataFrame, at: str, width: str, group: Sequence[str] = ()) -> DataFrame:
    return _counts(changes, F.window(at, width), group)


def sliding_counts(changes: DataFrame, at: str, width: str, slide: str, group: Sequence[str] = ()) -> DataFrame:
    """Changes per sliding window; of the log, not a temporal aggregate over a history."""
    return _counts(changes, F.window(at, width, slide), group)


def session_counts(changes: DataFrame, at: str, gap: str, group: Sequence[str] = ()) -> DataFrame:
    return _counts(changes, F.session_window(at, gap), group)


def _counts(changes: DataFrame, window, group: Sequence[str]) -> DataFrame:
    counts = changes.groupBy(*group, window.alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return counts.select(*group, F.col("w.start").alias("w_from"), F.col("w.end").alias("w_to"), "n")
