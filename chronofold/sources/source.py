"""The layout as a data source: ``format("clipped_layout")`` gives a window's segments, one input partition a file of the
chunks that the window touches.

The plain Parquet reader with the planner's filters stays the main path, as it runs in the JVM; this one serves users who name
a window rather than chunks.  Files are listed on the driver by Spark, so any store that Spark reads will do there; workers
open them by ``pyarrow``, for the stores that it knows.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

from ..functions.instants import FROM, TO
from ..spec import QueryWindow
from .layout import Layout


class File(InputPartition):
    def __init__(self, path: str, chunk: int) -> None:
        self.path, self.chunk = path, chunk


class Reader(DataSourceReader):
    def __init__(self, schema: StructType, options: dict[str, str]) -> None:
        self.names = [n for n in schema.names if n != "chunk"]
        self.low, self.high = options["low"], options["high"]
        self.files = json.loads(options["files"])

    def partitions(self) -> list[File]:
        return [File(path, chunk) for path, chunk in self.files]

    def read(self, partition: File) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute as pc
        import pyarrow.dataset as ds
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(partition.path)
        data = ds.dataset(path, filesystem=store, format="parquet", partitioning=None)
        kind = data.schema.field(FROM).type
        low, high = (pa.scalar(int(x), pa.int64()).cast(kind) for x in (self.low, self.high))
        for batch in data.to_batches(columns=self.names, filter=(pc.field(FROM) < high) & (pc.field(TO) > low)):
            columns = dict(zip(self.names, batch.columns, strict=True))
            if "is_head" in columns:
                columns["is_head"] = pc.and_(columns["is_head"], pc.greater_equal(columns[FROM], low))
            columns[FROM], columns[TO] = pc.max_element_wise(columns[FROM], low), pc.min_element_wise(columns[TO], high)
            chunk = pa.array([partition.chunk] * batch.num_rows, pa.int32())
            yield pa.RecordBatch.from_arrays([*columns.values(), chunk], names=[*self.names, "chunk"])


class ClippedLayout(DataSource):
    """Options: files (JSON pairs of path and chunk), low and high (microseconds, or steps), schema (DDL given by the caller)."""

    @classmethod
    def name(cls) -> str:
        return "clipped_layout"

    def reader(self, schema: StructType) -> Reader:
        return Reader(schema, self.options)


def read(spark: SparkSession, layout: Layout, window: QueryWindow) -> DataFrame:
    """Segments of a window; as many paths go to the driver as its chunks have files."""
    from ..functions.instants import to_axis

    spark.dataSource.register(ClippedLayout)
    first, last = layout.grid.chunks_for(window)
    rows = layout.scan(spark).where(F.col("chunk").between(first, last))
    files = [(r.f, r.chunk) for r in rows.select(F.col("_metadata.file_path").alias("f"), "chunk").distinct().collect()]
    names = [n for n in rows.columns if n != "chunk"] + ["chunk"]
    schema = StructType([rows.schema[n] for n in names])
    options = {"files": json.dumps(files), "low": str(to_axis(window.start)), "high": str(to_axis(window.end))}
    return spark.read.format("clipped_layout").schema(schema).options(**options).load()
