"""The clipped layout: a history cut at fixed instants, each chunk holding every (trimmed) row that shapes it.

Files lie under ``chunk=<n>``; within a chunk rows are sorted by bucket and key, so a range of buckets, or a key, skips row
groups.  Buckets are a column, not folders: chunks times buckets would be a flood of small files.
"""

from __future__ import annotations

import bisect
import datetime as dt
from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO, from_micros, instant, micros, on_axis, to_axis
from ..spec import HistorySpec, Instant, QueryWindow

BUCKETS = 4096
_MONTHS = {"MONTH": 1, "QUARTER": 3, "YEAR": 12}
_WIDTHS = {"HOUR": 3_600_000_000, "DAY": 86_400_000_000, "WEEK": 7 * 86_400_000_000}


@dataclass(frozen=True)
class ChunkGrid:
    """Ascending boundaries, fixed before any query; chunk n is [start(n), start(n + 1)).

    ``kind``: calendar (``months`` per chunk), uniform (``width`` in microseconds or steps, from ``origin``), explicit
    (``bounds``; what lies outside belongs to the chunks -1 and len(bounds) - 1, which are open to that side), or whole (one).
    """

    kind: str
    months: int = 0
    width: int = 0
    origin: int = 0
    bounds: tuple = ()
    integer: bool = False

    @staticmethod
    def calendar(unit: str) -> ChunkGrid:
        """MONTH, QUARTER or YEAR; HOUR, DAY and WEEK are uniform."""
        unit = unit.upper()
        return ChunkGrid("calendar", months=_MONTHS[unit]) if unit in _MONTHS else ChunkGrid("uniform", width=_WIDTHS[unit])

    @staticmethod
    def uniform(width: dt.timedelta | int, origin: Instant | None = None) -> ChunkGrid:
        """A width of time, or of steps on an integer axis."""
        integer = isinstance(width, int)
        return ChunkGrid("uniform", width=width if integer else width // dt.timedelta(microseconds=1), origin=to_axis(origin) if origin is not None else 0, integer=integer)

    @staticmethod
    def explicit(bounds: Sequence[Instant]) -> ChunkGrid:
        return ChunkGrid("explicit", bounds=tuple(sorted(set(bounds))), integer=isinstance(bounds[0], int))

    @staticmethod
    def whole() -> ChunkGrid:
        return ChunkGrid("whole")

    def scale(self, factor: float) -> ChunkGrid:
        """Chunks wider or narrower by a factor: whole months where that is possible, 30-day months otherwise."""
        if self.kind == "calendar" and float(self.months * factor).is_integer():
            return ChunkGrid("calendar", months=int(self.months * factor))
        width = self.width if self.kind == "uniform" else self.months * 30 * _WIDTHS["DAY"]
        return ChunkGrid("uniform", width=max(1, int(width * factor)), origin=self.origin, integer=self.integer)

    @property
    def days(self) -> int:
        """Days of a chunk, whose instants are then counted by date; 0 where a boundary may not be a midnight."""
        whole = self.kind == "uniform" and not self.integer and self.width % _WIDTHS["DAY"] == 0 and self.origin % _WIDTHS["DAY"] == 0
        return self.width // _WIDTHS["DAY"] if whole else 0

    def of(self, at: Column) -> Column:
        """Chunk of an instant column."""
        if self.kind == "whole":
            return F.lit(0)
        if self.kind == "calendar":
            return F.floor((F.year(at) * 12 + F.month(at) - 1) / self.months).cast("int")
        if self.days:
            return F.floor((F.unix_date(at.cast("date")) - self.origin // _WIDTHS["DAY"]) / self.days).cast("int")
        if self.kind == "uniform":
            v = at.cast("long") if self.integer else micros(at)
            return F.floor((v - self.origin) / F.lit(self.width)).cast("int")
        values = F.array(*(instant(b) for b in self.bounds))
        return F.size(F.filter(values, lambda b: b <= at)) - 1

    def last(self, end: Column) -> Column:
        """Chunk of the last instant before ``end``: intervals are open on the right."""
        if self.days:
            of = self.of(end)
            return of - (self.start(of) == end).cast("int")
        return self.of(end.cast("long") - 1) if self.integer else self.of(F.timestamp_add("MICROSECOND", F.lit(-1), end))

    def start(self, chunk: Column) -> Column:
        """First instant of a chunk; null where it is open to the left."""
        if self.kind == "whole":
            return F.lit(None).cast("timestamp_ntz")
        if self.kind == "calendar":
            month = chunk * self.months
            return F.make_date(F.floor(month / 12).cast("int"), F.pmod(month, F.lit(12)).cast("int") + 1, F.lit(1)).cast("timestamp_ntz")
        if self.days:
            return F.date_from_unix_date((chunk * self.days + self.origin // _WIDTHS["DAY"]).cast("int")).cast("timestamp_ntz")
        if self.kind == "uniform":
            v = chunk.cast("long") * self.width + self.origin
            return v if self.integer else from_micros(v)
        return F.try_element_at(F.array(*(instant(b) for b in self.bounds)), F.when(chunk >= 0, chunk + 1))

    def id_of(self, at: Instant) -> int:
        """The driver's counterpart of ``of``."""
        if self.kind == "whole":
            return 0
        if self.kind == "calendar":
            return (at.year * 12 + at.month - 1) // self.months
        if self.kind == "uniform":
            return (to_axis(at) - self.origin) // self.width
        return bisect.bisect_right(self.bounds, at) - 1

    def chunks_for(self, window: QueryWindow) -> tuple[int, int]:
        """First and last chunk that a window touches."""
        before = window.end - 1 if isinstance(window.end, int) else window.end - dt.timedelta(microseconds=1)
        return self.id_of(window.start), self.id_of(max(before, window.start))


def bucket_of(keys: Sequence[str], buckets: int = BUCKETS) -> Column:
    return F.pmod(F.xxhash64(*keys), F.lit(buckets)).cast("int")


def clip_to_chunks(history: DataFrame, grid: ChunkGrid, keys: Sequence[str], buckets: int = BUCKETS) -> DataFrame:
    """Every row copied into each chunk it touches and cut to it, with chunk, bucket and is_head (the piece with the row's own
    start).  Ends must be closed (see a history's horizon)."""
    spread = history.withColumn("chunk", F.explode(F.sequence(grid.of(F.col(FROM)), grid.last(F.col(TO)))))
    low, high = grid.start(F.col("chunk")), grid.start(F.col("chunk") + 1)
    # greatest and least pass over nulls, so chunks open to a side need no case
    cut = spread.withColumns({"is_head": F.coalesce(F.col(FROM) >= low, F.lit(True)), FROM: F.greatest(F.col(FROM), low), TO: F.least(F.col(TO), high)})
    return cut.withColumn("bucket", bucket_of(keys, buckets))


@dataclass(frozen=True)
class Layout:
    """A built layout; ``manifest`` is a Parquet table beside it: chunk, bucket_lo, bucket_hi, rows, min_from, max_to, schema_json."""

    path: str
    grid: ChunkGrid
    spec: HistorySpec
    buckets: int = BUCKETS

    def manifest(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.path}/manifest")

    def scan(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.path}/data")

    def spans(self, spark: SparkSession, window: QueryWindow) -> dict[int, tuple[int, int]]:
        """First and last instant of each chunk's rows within a window, as numbers (see on_axis); from the manifest alone."""
        first, last = self.grid.chunks_for(window)
        known = self.manifest(spark).where(F.col("chunk").between(first, last))
        ends = {r.chunk: (max(r.low, to_axis(window.start)), min(r.high, to_axis(window.end))) for r in known.select("chunk", on_axis(known, "min_from").alias("low"), on_axis(known, "max_to").alias("high")).collect()}
        return {c: (low, high) for c, (low, high) in ends.items() if low < high}


def build_clipped_layout(history: DataFrame, grid: ChunkGrid, path: str, spec: HistorySpec, buckets: int = BUCKETS, bucket_groups: int = 8, max_records: int = 0) -> Layout:
    """Write the layout: one shuffle, by chunk and range of buckets, then sorted files.  ``bucket_groups``: files of a chunk, at most.
    Chunks are overwritten one by one, so a build may run in waves of chunks and be repeated."""
    rows = clip_to_chunks(history.select(*spec.columns), grid, spec.keys, buckets)
    group = F.floor(F.col("bucket") * bucket_groups / buckets).cast("int")
    placed = rows.withColumn("_g", group).repartition("chunk", "_g").drop("_g").sortWithinPartitions("chunk", "bucket", *spec.keys, FROM)
    writer = placed.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("chunk")
    if max_records:
        writer = writer.option("maxRecordsPerFile", max_records)
    writer.parquet(f"{path}/data")
    layout = Layout(path, grid, spec, buckets)
    write_manifest(history.sparkSession, layout)
    return layout


def write_manifest(spark: SparkSession, layout: Layout) -> None:
    data = layout.scan(spark)
    sums = data.groupBy("chunk").agg(F.min("bucket").alias("bucket_lo"), F.max("bucket").alias("bucket_hi"), F.count(F.lit(1)).alias("rows"), F.min(FROM).alias("min_from"), F.max(TO).alias("max_to"))
    sums.withColumn("schema_json", F.lit(data.schema.json())).coalesce(1).write.mode("overwrite").parquet(f"{layout.path}/manifest")


def read_layout(spark: SparkSession, layout: Layout, window: QueryWindow, buckets: tuple[int, int] | None = None, keys: Sequence | None = None) -> DataFrame:
    """Segments of a window: chunks pruned by folder, buckets and keys by row group, edges of the window cut.

    Catalyst can't infer chunks from an overlap, so they are stated.
    """
    first, last = layout.grid.chunks_for(window)
    rows = layout.scan(spark).where(F.col("chunk").between(first, last))
    if buckets is not None:
        rows = rows.where(F.col("bucket").between(*buckets))
    if keys is not None:
        rows = rows.where(F.col(layout.spec.keys[0]).isin(*keys))
    rows = rows.where((F.col(FROM) < window.high) & (F.col(TO) > window.low))
    return rows.withColumns({"is_head": F.col("is_head") & (F.col(FROM) >= window.low), FROM: F.greatest(F.col(FROM), window.low), TO: F.least(F.col(TO), window.high)})


def segments(history: DataFrame, grid: ChunkGrid, keys: Sequence[str], window: QueryWindow) -> DataFrame:
    """The same segments without a stored layout."""
    from .history import restrict_window

    return clip_to_chunks(restrict_window(history, window), grid, keys)


def write_scd2(history: DataFrame, path: str) -> None:
    """The unclipped source: rows under the month of their start."""
    month = F.year(FROM) * 12 + F.month(FROM) - 1
    history.withColumn("from_month", month).repartition("from_month").sortWithinPartitions("from_month", FROM).write.mode("overwrite").partitionBy("from_month").parquet(path)


def read_scd2_for_chunk(spark: SparkSession, path: str, window: QueryWindow) -> DataFrame:
    """Rows for a stretch of time from the unclipped source: every month up to it must be read, however old."""
    last = ChunkGrid.calendar("MONTH").chunks_for(window)[1]
    from .history import restrict_window

    return restrict_window(spark.read.parquet(path).where(F.col("from_month") <= last).drop("from_month"), window)


def append_period(spark: SparkSession, layout: Layout, changes: DataFrame, at: str, upto: Instant, tie: Sequence[str] = ()) -> None:
    """Add a period of changes after the layout's end: rows that last to the old end go on until their key changes.

    Only chunks from the one of the old end are written again.
    """
    from .history import from_change_log

    spec, grid = layout.spec, layout.grid
    ends = layout.manifest(spark).agg(F.max("max_to").alias("m"), F.max("chunk").alias("c")).first()
    old_end, chunk = ends.m, ends.c
    old = layout.scan(spark).where(F.col("chunk") == chunk)
    carried = old.where(F.col(TO) == instant(old_end))
    log = carried.select(*spec.keys, *spec.payload, F.col(FROM).alias(at), *(F.lit(None).cast(changes.schema[t].dataType).alias(t) for t in tie)).unionByName(changes.select(*spec.keys, *spec.payload, at, *tie))
    fresh = clip_to_chunks(from_change_log(log, spec.keys, at, spec.payload, tie, upto), grid, spec.keys, layout.buckets)
    heads = carried.where("NOT is_head").select(*spec.keys, F.lit(True).alias("_carried"), F.col(FROM).alias("_f"))
    fresh = fresh.join(heads, [fresh[k].eqNullSafe(heads[k]) for k in spec.keys] + [fresh[FROM] == heads["_f"]], "left_anti").unionByName(
        fresh.join(heads, [fresh[k].eqNullSafe(heads[k]) for k in spec.keys] + [fresh[FROM] == heads["_f"]], "left_semi").withColumn("is_head", F.lit(False))
    )
    whole = old.where(F.col(TO) < instant(old_end)).unionByName(fresh.select(*old.columns))
    stage = f"{layout.path}/stage"
    whole.write.mode("overwrite").parquet(stage)
    spark.read.parquet(stage).repartition("chunk").sortWithinPartitions("chunk", "bucket", *spec.keys, FROM).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("chunk").parquet(f"{layout.path}/data")
    write_manifest(spark, layout)


def build_cohort_layout(spark: SparkSession, layout: Layout, cohort_rows: DataFrame, path: str) -> Layout:
    """A layout of one cohort's rows alone, in one bucket; answers are those of the full layout with pruned keys."""
    rows = layout.scan(spark).join(cohort_rows.select(*layout.spec.keys).distinct(), list(layout.spec.keys), "left_semi").withColumn("bucket", F.lit(0))
    rows.repartition("chunk").sortWithinPartitions("chunk", *layout.spec.keys, FROM).write.mode("overwrite").partitionBy("chunk").parquet(f"{path}/data")
    own = Layout(path, layout.grid, layout.spec, 1)
    write_manifest(spark, own)
    return own
