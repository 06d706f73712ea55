"""The mutable tier: blind appends, resolved at read time or by compaction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from histreplay.operators.history import sequences
from histreplay.schema import EVENT_COLUMNS


def fragments(events: DataFrame, span: int) -> DataFrame:
    """What blind appends leave: for each user and write (a span of time here) an unordered list, repeats included."""
    return events.groupBy("user_id", F.floor(F.col("us") / span).alias("write_no")).agg(F.collect_list(F.struct(*EVENT_COLUMNS)).alias("ev"))


def append(path: str, events: DataFrame, span: int) -> None:
    """Adds fragments to the tier's files; nothing is read."""
    fragments(events, span).write.mode("append").parquet(path)


def compact(parts: DataFrame) -> DataFrame:
    """One fragment a user, repeats gone: the background form of the resolution."""
    return parts.groupBy("user_id").agg(F.array_distinct(F.flatten(F.collect_list("ev"))).alias("ev")).withColumn("write_no", F.lit(0).cast("long"))


def resolve(parts: DataFrame, now_us: int, retention: int) -> DataFrame:
    """Read-time resolution: the latest `retention` of each user, ordered, each event once, as arrays."""
    rows = parts.select("user_id", F.inline("ev")).filter((F.col("us") >= now_us - retention) & (F.col("us") <= now_us))
    return sequences(rows.dropDuplicates(["user_id", "event_id"]), ["user_id"])


def cache(parts: DataFrame) -> DataFrame:
    """A copy beside the reader; unpersist() ends it."""
    return parts.persist(StorageLevel.MEMORY_AND_DISK)
