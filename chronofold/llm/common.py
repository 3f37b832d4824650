"""What the corpus operators share: table reading, the shared work folder and small expressions."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def work_folder(spark: SparkSession) -> str:
    """A new folder under ``spark.checkpoint.dir``; where that is unset, a temporary one in local mode (as in tests) and
    the warehouse otherwise."""
    conf = spark.sparkContext.getConf()
    top = conf.get("spark.checkpoint.dir", None)
    if not top:
        top = tempfile.gettempdir() if spark.sparkContext.master.startswith("local[") else spark.conf.get("spark.sql.warehouse.dir")
        if spark.sparkContext.master.startswith("local["):
            top = f"file://{top}"
    return f"{top}/chronofold-{uuid.uuid4().hex}"


#: Folders written within each open ``temporary`` block.
_OPEN: list[list[str]] = []
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def spool(df: DataFrame, compression: str = "zstd") -> DataFrame:
    """Write a table to the shared work folder and read it back: later reads neither recompute it nor need the executors
    that made it.  Its shuffle files go when it is written."""
    spark = df.sparkSession
    path = work_folder(spark)
    if _OPEN:
        _OPEN[-1].append(path)
    before = spark.conf.get(_CLEANUP, "false")
    try:
        spark.conf.set(_CLEANUP, "true")
        df.select("*").write.option("compression", compression).parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._folder = path  # for ``discard``
    return out


def discard(spooled: DataFrame) -> None:
    """Delete a spooled table that nothing reads any more."""
    for folders in _OPEN:
        if spooled._folder in folders:
            folders.remove(spooled._folder)
    delete(spooled.sparkSession, spooled._folder)


def delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


@contextmanager
def temporary(spark: SparkSession) -> Iterator[None]:
    """Folders that ``spool`` writes within the block are deleted at its end; a result that reads them has to be spooled
    outside, or by ``finished``."""
    _OPEN.append([])
    try:
        yield
    finally:
        for path in _OPEN.pop():
            delete(spark, path)


def finished(df: DataFrame) -> DataFrame:
    """``df`` spooled as part of what surrounds the present ``temporary`` block."""
    inner = _OPEN.pop() if _OPEN else None
    try:
        return spool(df)
    finally:
        if inner is not None:
            _OPEN.append(inner)


#: Parts that the rows of one key are dealt to before a join; a key that few rows have is in as few parts.
PARTS = 256


def part_of(by: str | Column) -> Column:
    return F.pmod(F.xxhash64(by), F.lit(PARTS)).cast("int")


def spread_join(left: DataFrame, right: DataFrame, on: list[str], by: str) -> DataFrame:
    """``left`` inner joined to ``right`` (one row a key) where a key may hold a large share of ``left``: its rows are dealt by
    a hash of ``by``, and the right row is copied to the parts that the key has, so no task gets all of them."""
    dealt = left.withColumn("_part", part_of(by))
    copied = dealt.select(*on, "_part").distinct().join(right, on)
    return dealt.join(copied, [*on, "_part"]).drop("_part")


def remainder(doc_id: str | Column, modulus: int) -> Column:
    """crc32 of an id as text, modulo ``modulus``; a null id counts as the empty text."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.crc32(F.coalesce(c.cast("string"), F.lit(""))) % modulus


def tidy(each: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``each``, after which the worker gives its free memory back: workers live on from stage to stage."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from each(batches)
        finally:
            give_back()

    return run


def give_back() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not glibc
        pass


def parts_of(df: DataFrame) -> int:
    """Partitions that the table's scan has: follows the size of its files."""
    return max(1, df.rdd.getNumPartitions())


def range_bounds(df: DataFrame, column: str, ranges: int) -> list[int]:
    """At most ``ranges`` - 1 ascending values of a long column that split its rows about evenly.  One job over that column
    alone; the sketch's size follows ``ranges``, not the rows."""
    if ranges < 2:
        return []
    probs = [i / ranges for i in range(1, ranges)]
    values = df.select(F.col(column).cast("long").alias("v")).stat.approxQuantile("v", probs, min(0.01, 0.2 / ranges))
    return sorted({int(v) for v in values})
