"""Clustering of examples by user and time, and equal sharding of both sides."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.schema import HOUR


def lookups(requests: DataFrame, window: int = HOUR) -> DataFrame:
    """(user_id, slot, requests): one lookup serves all requests of a user in a window of time."""
    return requests.groupBy("user_id", F.floor(F.col("t_us") / window).alias("slot")).agg(F.count("*").alias("requests"))


def session_lookups(requests: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """As lookups, for sessions that a gap ends."""
    at = F.timestamp_micros("t_us")
    return requests.withColumn("at", at).groupBy("user_id", F.session_window("at", gap).alias("w")).agg(F.count("*").alias("requests")).select("user_id", F.unix_micros("w.start").alias("slot"), "requests")


def cluster(slim: DataFrame, buckets: int, table: str, window: int = HOUR) -> None:
    """Writes examples by window, bucketed and sorted by user: one task meets a user's requests side by side."""
    rows = slim.withColumn("slot", F.floor(F.col("t_us") / window))
    ready = rows.repartition(buckets, "user_id").sortWithinPartitions("slot", "user_id", "t_us")
    ready.write.mode("overwrite").partitionBy("slot").bucketBy(buckets, "user_id").sortBy("user_id", "t_us").saveAsTable(table)


def co_shard(slim: DataFrame, stripes: DataFrame, buckets: int, names: tuple[str, str], symmetric: bool = True) -> tuple[DataFrame, DataFrame]:
    """Both sides as tables in the same buckets of the same key, so that their join needs no shuffle.

    symmetric=False is the control: the examples are bucketed otherwise.
    """
    spark = slim.sparkSession
    for df, name, n in ((slim, names[0], buckets if symmetric else buckets + 3), (stripes, names[1], buckets)):
        df.repartition(n, "user_id").write.mode("overwrite").bucketBy(n, "user_id").sortBy("user_id").saveAsTable(name)
    return spark.table(names[0]), spark.table(names[1])


def fanout(batched: DataFrame, shards: int) -> DataFrame:
    """(batch_id, shards) that a loading batch touches; a user is in shard user_id mod shards."""
    return batched.groupBy("batch_id").agg(F.count_distinct(F.pmod("user_id", F.lit(shards))).alias("shards"))
