"""One stream of events for online training and for hourly tables, and its windows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from histreplay.schema import HOUR


def source(spark: SparkSession, path: str, like: DataFrame, files: int = 10) -> DataFrame:
    """A stream of the Parquet files that arrive in a folder, with the schema of `like`."""
    return spark.readStream.schema(like.schema).option("maxFilesPerTrigger", files).parquet(path)


def to_table(stream: DataFrame, path: str, checkpoint: str, batch: Callable[[DataFrame, int], DataFrame] | None = None, mode: str = "append"):
    """Runs what is there through and ends; each batch goes to its own folder, so a repeated batch replaces itself."""

    def write(df: DataFrame, number: int) -> None:
        out = df if batch is None else batch(df, number)
        out.write.mode("overwrite").parquet(f"{path}/batch={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return query


def hourly(stream: DataFrame, path: str, checkpoint: str, online: Callable[[DataFrame, int], None] | None = None) -> None:
    """Persists events by hour and hands the same batch to an online trainer: one read of the stream serves both."""

    def write(df: DataFrame, number: int) -> None:
        df = df.persist()
        hours = df.withColumns({"hour": F.floor(F.col("us") / HOUR), "batch": F.lit(number)})
        hours.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("hour", "batch").parquet(path)
        if online is not None:
            online(df, number)
        df.unpersist()

    stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def timed(stream: DataFrame) -> DataFrame:
    return stream.withColumn("at", F.timestamp_micros("us"))


def tumbling(stream: DataFrame, width: str, late: str) -> DataFrame:
    w = F.window("at", width)
    return timed(stream).withWatermark("at", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.unix_micros("w.start").alias("from_us"), "event_type", "n")


def sliding(stream: DataFrame, width: str, step: str, late: str) -> DataFrame:
    return timed(stream).withWatermark("at", late).groupBy(F.window("at", width, step).alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("value")).select(F.unix_micros("w.start").alias("from_us"), "n", F.round("value", 4).alias("value"))


def sessions(stream: DataFrame, gap: str, late: str) -> DataFrame:
    return timed(stream).withWatermark("at", late).groupBy("user_id", F.session_window("at", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.unix_micros("w.start").alias("from_us"), "n")


def deduped(stream: DataFrame, late: str) -> DataFrame:
    """Each event once, for repeats within the watermark."""
    return timed(stream).withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"]).drop("at")


def split_late(batch: DataFrame, seen_us: int, late_us: int) -> tuple[DataFrame, DataFrame]:
    """(in time, late) by a watermark of one's own, for a side table of late rows."""
    limit = seen_us - late_us
    return batch.filter(F.col("us") >= limit), batch.filter(F.col("us") < limit)


def label_join(requests: DataFrame, labels: DataFrame, horizon: str, late: str) -> DataFrame:
    """Requests and the positive events within the horizon, both streams; unlabelled requests come out when they can't be hit any more."""
    a = requests.withColumn("t", F.timestamp_micros("t_us")).withWatermark("t", late)
    b = labels.select(F.col("user_id").alias("label_user"), F.col("us").alias("label_us"), F.timestamp_micros("us").alias("lt")).withWatermark("lt", late)
    near = (F.col("user_id") == F.col("label_user")) & (F.col("lt") > F.col("t")) & F.expr(f"lt <= t + interval {horizon}")
    return a.join(b, near, "leftOuter").select("request_id", "user_id", "t_us", "label_us")
