"""Layered layout: dense groups looked back on for a short time, sparse ones for long."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.schema import DAY


def build(hist: DataFrame, lookbacks: dict[str, int], as_of: int) -> DataFrame:
    """The events of each group's own lookback before as_of; groups without one are dropped."""
    days = F.create_map(*[F.lit(x) for pair in lookbacks.items() for x in pair])[F.col("feature_group")]
    return hist.filter((F.col("us") < as_of) & (F.col("us") >= F.lit(as_of) - days * F.lit(DAY)))


def of_requests(rows: DataFrame, lookbacks: dict[str, int]) -> DataFrame:
    """Window events (request_id, cutoff_us, us, feature_group) within each group's own lookback."""
    days = F.create_map(*[F.lit(x) for pair in lookbacks.items() for x in pair])[F.col("feature_group")]
    return rows.filter(F.col("us") >= F.col("cutoff_us") - (days - 1) * F.lit(DAY))


def plan(hist: DataFrame, dense_share: float = 0.15, dense_days: int = 7, sparse_days: int = 30) -> DataFrame:
    """(event_type, share, feature_group, days): types with at least dense_share of the events are dense."""
    counts = hist.groupBy("event_type").agg(F.count("*").alias("n"))
    total = hist.agg(F.count("*").alias("total"))
    share = F.col("n") / F.col("total")
    dense = share >= dense_share
    return counts.crossJoin(F.broadcast(total)).select("event_type", share.alias("share"), F.when(dense, "dense").otherwise("sparse").alias("feature_group"), F.when(dense, dense_days).otherwise(sparse_days).alias("days"))
