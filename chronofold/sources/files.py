"""Reading and writing tables."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def load(spark: SparkSession, folder: str, table: str, columns: Sequence[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{folder}/{table}.parquet")
    return df.select(*columns) if columns else df


def load_changes(spark: SparkSession, path: str, fmt: str, schema: T.StructType, corrupt: str = "_corrupt") -> DataFrame:
    """A change log as csv, json or orc, with a stated schema; rows that csv or json can't parse keep their text in ``corrupt``."""
    if fmt == "orc":
        return spark.read.schema(schema).orc(path)
    wide = T.StructType([*schema.fields, T.StructField(corrupt, T.StringType())])
    return spark.read.format(fmt).schema(wide).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", corrupt).load(path)


def write_result(df: DataFrame, path: str, query: str) -> None:
    """A result under its query's name, and a row in the result manifest."""
    df.write.mode("overwrite").parquet(f"{path}/{query}")
    spark = df.sparkSession
    n = spark.read.parquet(f"{path}/{query}").count()
    spark.createDataFrame([(query, n, df.schema.json())], "query string, rows long, schema_json string").coalesce(1).write.mode("append").parquet(f"{path}/manifest")


def register(df: DataFrame, name: str) -> None:
    df.createOrReplaceTempView(name)


def rows(spark: SparkSession, values: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(values, schema)


def sample(df: DataFrame, share: float, seed: int = 7) -> DataFrame:
    """For sizing estimates only."""
    return df.sample(share, seed)


def props(df: DataFrame, column: str = "props", schema: str = "k BIGINT") -> DataFrame:
    """A JSON column as a struct of the same name."""
    return df.withColumn(column, F.from_json(column, schema))
