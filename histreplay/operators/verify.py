"""Checks of replayed sequences against what was logged or served."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.functions.digest import additive, event_hash


def check(replayed: DataFrame, logged: DataFrame, projected: bool = False, tombstones: DataFrame | None = None) -> DataFrame:
    """(request_id, status): ok, length_mismatch, digest_mismatch, missing, scrubbed or unverifiable_projected.

    replayed has request_id, user_id and arrays us, event_id of the immutable part; logged has request_id, seq_len and
    an additive digest. tombstones (user_id) names histories from which a build has deleted events.
    """
    total = F.aggregate(F.zip_with("us", "event_id", event_hash), F.lit(0).cast("long"), lambda a, b: a + b)
    found = replayed.select("request_id", "user_id", F.size("us").alias("n"), additive(total).cast("string").alias("found"))
    both = logged.select("request_id", "seq_len", "digest").join(found, "request_id", "left")
    gone = F.lit(False)
    if tombstones is not None:
        both = both.join(tombstones.select("user_id").distinct().withColumn("__gone", F.lit(True)), "user_id", "left")
        gone = F.coalesce("__gone", F.lit(False))
    ok = (F.col("n") == F.col("seq_len")) & ((F.col("found") == F.col("digest")) | F.col("digest").isNull())
    status = F.when(F.lit(projected), "unverifiable_projected").when(ok, "ok").when(gone, "scrubbed").when(F.col("n").isNull(), "missing").when(F.col("n") != F.col("seq_len"), "length_mismatch").otherwise("digest_mismatch")
    return both.select("request_id", status.alias("status"))


def rate(checked: DataFrame) -> DataFrame:
    """(checked, ok, share)."""
    ok = F.count_if(F.col("status") == "ok")
    return checked.agg(F.count("*").alias("checked"), ok.alias("ok"), (ok / F.count("*")).alias("share"))


def leakage(rows: DataFrame) -> DataFrame:
    """(leaked_events, leaked_requests) of event rows with request_id, t_us and us."""
    late = F.col("us") > F.col("t_us")
    return rows.agg(F.count_if(late).alias("leaked_events"), F.count_distinct(F.when(late, F.col("request_id"))).alias("leaked_requests"))


def freshness(seq: DataFrame) -> DataFrame:
    """(request_id, lag_us): from the newest event of each sequence to the request; null without events."""
    return seq.select("request_id", (F.col("t_us") - F.array_max("us")).alias("lag_us"))
