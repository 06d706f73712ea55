"""The given tables. Zone-free times become epoch microseconds here, once, whatever the session's zone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(ts: str | Column) -> Column:
    """Epoch microseconds of a zone-free timestamp."""
    ts = F.col(ts) if isinstance(ts, str) else ts
    return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), ts)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").withColumn("us", micros("ts"))


def nation_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events keyed by the user's nation: longer histories. customer is a dimension, joined by shuffle or broadcast as its size allows."""
    users = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), F.col("c_nationkey").cast("long").alias("nation"))
    return events(spark, sf_dir).join(users, "user_id").withColumn("user_id", F.col("nation")).drop("nation")


def region_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events keyed by the user's region: the longest histories."""
    regions = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("user_id"), F.col("n_regionkey").cast("long").alias("region"))
    return nation_events(spark, sf_dir).join(F.broadcast(regions), "user_id").withColumn("user_id", F.col("region")).drop("region")


KEYED = {"user": events, "nation": nation_events, "region": region_events}
