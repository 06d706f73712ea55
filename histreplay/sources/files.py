"""Imports and exports in other formats; schemas are always given, never inferred."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

FORMATS = ("parquet", "orc", "json", "csv")


def write(df: DataFrame, path: str, kind: str = "parquet", partition: str | None = None) -> None:
    writer = df.write.mode("errorifexists").format(kind)
    if kind == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(partition) if partition else writer).save(path)


def read(spark: SparkSession, path: str, schema: T.StructType, kind: str = "parquet") -> DataFrame:
    reader = spark.read.schema(schema).format(kind)
    return (reader.option("header", True) if kind == "csv" else reader).load(path)
