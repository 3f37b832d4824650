"""How wide chunks and how many shards should be."""

from __future__ import annotations

import math
from collections.abc import Callable, Mapping, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.instants import FROM, TO, length
from ..sources.layout import ChunkGrid, Layout, bucket_of


def row_amplification(history: DataFrame, grids: Mapping[str, ChunkGrid]) -> DataFrame:
    """(width, source_rows, layout_rows, a_row) of many grids from one scan, without building any."""
    spans = [F.sum((g.last(F.col(TO)) - g.of(F.col(FROM)) + 1).cast("long")).alias(f"_{i}") for i, g in enumerate(grids.values())]
    sums = history.agg(F.count(F.lit(1)).alias("source_rows"), *spans)
    each = F.array(*(F.struct(F.lit(n).alias("width"), F.col(f"_{i}").alias("layout_rows")) for i, n in enumerate(grids)))
    out = sums.select("source_rows", F.explode(each).alias("w")).select("w.width", "source_rows", "w.layout_rows")
    return out.withColumn("a_row", F.round(F.col("layout_rows") / F.col("source_rows"), 6))


def mean_lifetime(history: DataFrame) -> float:
    """Mean length of a row in microseconds."""
    return history.agg(F.avg(length(F.col(FROM), F.col(TO)))).first()[0] or 0.0


def predict_amplification(mean_life: float, width: float, granule: float = 0.0) -> float:
    """1 + mean lifetime / width; starts and ends on a grain of time shorten each row by one grain."""
    return 1 + max(0.0, mean_life - granule) / width


def byte_amplification(spark: SparkSession, layout_path: str, source_path: str) -> float:
    """Bytes of the layout's files against the source's."""

    def size(path: str) -> int:
        files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").load(path)
        return files.agg(F.sum("length")).first()[0] or 0

    return size(layout_path) / max(1, size(source_path))


def storage_safe_width(history: DataFrame, candidates: Mapping[str, ChunkGrid], eps_rows: float, eps_bytes: float | None = None, bytes_of: Callable[[str], float] | None = None) -> str | None:
    """The first candidate (narrowest first) within both budgets; None: keep the whole window in one chunk.

    ``bytes_of`` gives a candidate's byte amplification (from a sample, or a build); without it only rows count.
    """
    found = {r.width: r.a_row for r in row_amplification(history, candidates).collect()}
    for name in candidates:
        if found[name] <= 1 + eps_rows and (bytes_of is None or eps_bytes is None or bytes_of(name) <= 1 + eps_bytes):
            return name
    return None


def key_byte_histogram(rows: DataFrame, keys: Sequence[str], row_bytes: float, buckets: int = 4096) -> DataFrame:
    """(chunk, bucket, rows, bytes): estimated bytes by key bucket; chunks times buckets rows, whatever the data."""
    sized = rows if "bucket" in rows.columns else rows.withColumn("bucket", bucket_of(keys, buckets))
    return sized.groupBy("chunk", "bucket").agg(F.count(F.lit(1)).alias("rows")).withColumn("bytes", F.col("rows") * F.lit(row_bytes))


def heaviest_keys(rows: DataFrame, keys: Sequence[str], row_bytes: float, top: int = 20) -> DataFrame:
    return rows.groupBy("chunk", *keys).agg(F.count(F.lit(1)).alias("rows")).withColumn("bytes", F.col("rows") * F.lit(row_bytes)).orderBy(F.desc("bytes"), *keys).limit(top)


def plan_shards(histogram: DataFrame, ceiling: float) -> DataFrame:
    """(chunk, shard, bucket_lo, bucket_hi, bytes, over, parts): the fewest contiguous bucket ranges of each chunk within the ceiling.

    Filling each range as far as it goes needs the fewest ranges.  A bucket that alone exceeds the ceiling is its own range,
    marked ``over``; a plan cuts it into ``parts`` stretches of time at query time, which stores nothing twice.
    """
    spark = histogram.sparkSession
    out, now = [], None
    for r in histogram.orderBy("chunk", "bucket").collect():  # chunks x buckets rows, a parameter of the layout
        if now is not None and now[0] == r.chunk and now[4] + r.bytes <= ceiling:
            now[3], now[4] = r.bucket, now[4] + r.bytes
            continue
        now = [r.chunk, now[1] + 1 if now is not None and now[0] == r.chunk else 0, r.bucket, r.bucket, r.bytes]
        out.append(now)
    return spark.createDataFrame([(*x, x[4] > ceiling, max(1, math.ceil(x[4] / ceiling))) for x in out], "chunk int, shard int, bucket_lo int, bucket_hi int, bytes double, over boolean, parts int")


def calibrate_ceiling(candidates: Sequence[float], probe: Callable[[float], Mapping[str, bool]]) -> tuple[float | None, list[dict]]:
    """The largest piece size for which every query of ``probe`` ends without spill; tries sizes upward and records each."""
    best, record = None, []
    for size in sorted(candidates):
        found = probe(size)
        record.append({"bytes": size, "ok": all(found.values()), **found})
        if not all(found.values()):
            break
        best = size
    return best, record


def shards_with_retry(histogram: DataFrame, ceiling: float, run: Callable[[DataFrame], bool], tries: int = 3) -> DataFrame:
    """Shards that run within memory: a piece that fails asks for a smaller ceiling before the plan gives up."""
    for _ in range(tries):
        shards = plan_shards(histogram, ceiling)
        if run(shards):
            return shards
        ceiling /= 2
    raise RuntimeError("pieces exceed memory at the smallest ceiling tried")


def amortized_queries(build_cost: float, per_query_before: float, per_query_after: float) -> float:
    """Queries until building a layout has paid."""
    saved = per_query_before - per_query_after
    return build_cost / saved if saved > 0 else float("inf")


def layout_sizes(spark: SparkSession, layout: Layout) -> DataFrame:
    return layout.manifest(spark).select("chunk", "rows", "min_from", "max_to").orderBy("chunk")
