"""Conveniences on replayed sequences; our own, not methods of the reference."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def topk_by_category(seq: DataFrame, category: Column, k: int, traits: tuple[str, ...] = ("us", "event_id", "event_type")) -> DataFrame:
    """The latest k events of a sequence whose type equals the candidate's category."""
    ev = F.filter(F.arrays_zip(*traits), lambda e: e["event_type"] == category)
    return seq.withColumn("top", F.slice(F.reverse(ev), F.lit(1), F.lit(k)))


def topk_by_vector(events: DataFrame, vectors: DataFrame, candidate: list[float], k: int) -> DataFrame:
    """(request_id, item_id, score): the k events (request_id, item_id) with the largest dot product."""
    cand = F.array(*[F.lit(float(x)) for x in candidate])
    dot = F.aggregate(F.zip_with(F.col("embedding"), cand, lambda a, b: a.cast("double") * b), F.lit(0.0), lambda s, x: s + x)
    scored = events.select("request_id", "item_id").distinct().join(vectors.select(F.col("vec_id").cast("int").alias("item_id"), dot.alias("score")), "item_id")
    order = Window.partitionBy("request_id").orderBy(F.col("score").desc(), "item_id")
    return scored.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def pair_count(n: Column, window: int | None = None) -> Column:
    """Pairs of causal attention over n events, or over bands of `window`."""
    if window is None:
        return (n * (n + 1) / 2).cast("long")
    w = F.least(n, F.lit(window))
    return (w * (w + 1) / 2 + (n - w) * window).cast("long")


def sample_length(request_id: Column, max_len: int, seed: int) -> Column:
    """A length in 1..max_len that request and seed decide."""
    text = F.md5(F.concat_ws(":", request_id.cast("string"), F.lit(str(seed))))
    return (F.conv(F.substring(text, 1, 8), 16, 10).cast("long") % max_len + 1).cast("int")
