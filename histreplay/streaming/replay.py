"""Replay of a stream of slim examples: the same functions as in batch, one pinned generation a micro-batch."""

from __future__ import annotations

from pyspark.sql import DataFrame

from histreplay.operators import history, replay
from histreplay.streaming.ingest import to_table


def run(slim: DataFrame, stripes: DataFrame, path: str, checkpoint: str, length: int | None = None, strategy: str = "affinity", stripe_len: int = 8) -> None:
    """Writes (request_id, n, first_us, last_us, digest) of each micro-batch."""
    to_table(slim, path, checkpoint, lambda df, number: history.summary(replay.reconstruct(df, stripes, length, strategy, stripe_len)))
