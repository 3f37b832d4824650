"""Functions for SQL users: an aggregate, and table functions usable with LATERAL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def twa_udaf():
    """Duration-weighted mean of (x, micros) as a grouped aggregate; nulls of x don't count."""
    @F.pandas_udf("double")
    def twa(x: pd.Series, duration: pd.Series) -> float:
        known = x.notna()
        total = duration[known].sum()
        return float((x[known].astype(float) * duration[known]).sum() / total) if total else None

    return twa


def chunk_pieces_udtf(width_us: int):
    """Table function: the pieces of [f, t) (microseconds) in uniform chunks: (chunk, f, t)."""

    @F.udtf(returnType="chunk: bigint, f: bigint, t: bigint")
    class ChunkPieces:
        def eval(self, f: int, t: int):
            if f is None or t is None:
                return
            for c in range(f // width_us, (t - 1) // width_us + 1 if t > f else f // width_us):
                yield c, max(f, c * width_us), min(t, (c + 1) * width_us)

    return ChunkPieces


def register(spark: SparkSession, width_us: int = 86_400_000_000) -> None:
    """SQL names: twa(x, micros), chunk_pieces(f, t), and the scalar overlap_us(f, t, ws, we)."""
    spark.udf.register("twa", twa_udaf())
    spark.udtf.register("chunk_pieces", chunk_pieces_udtf(width_us))
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION overlap_us(f TIMESTAMP_NTZ, t TIMESTAMP_NTZ, ws TIMESTAMP_NTZ, we TIMESTAMP_NTZ) RETURNS BIGINT "
        "RETURN greatest(0, timestampdiff(MICROSECOND, greatest(f, ws), least(t, we)))"
    )
