"""Preprocessing jobs: replay apart from the trainer, batches handed over by iterator or by files."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.operators import replay
from histreplay.plans.prefetch import ahead
from histreplay.schema import HOUR, TenantSpec


@dataclass(frozen=True)
class JobSpec:
    """A training job: its tenant, the hours of examples it reads (all if None), base batch rows and replay strategy."""

    tenant: TenantSpec
    hours: tuple[int, int] | None = None
    base_rows: int = 256
    strategy: str = "affinity"
    stripe_len: int = 8


def run(job: JobSpec, slim: DataFrame, stripes: DataFrame) -> DataFrame:
    """The job's examples with their sequences; hours prune before anything is replayed."""
    if job.hours is not None:
        lo, hi = job.hours
        slim = slim.filter((F.col("t_us") >= lo * HOUR) & (F.col("t_us") < hi * HOUR))
    traits = tuple(dict.fromkeys(("us", "event_id", *job.tenant.traits)))
    return replay.reconstruct(slim, stripes, job.tenant.seq_len, job.strategy, job.stripe_len, traits)


def run_many(jobs: list[JobSpec], slim: DataFrame, stripes: DataFrame) -> list[DataFrame]:
    """Many jobs on one pinned generation; they share the scan's files and Spark's scheduler, and no other state."""
    return [run(job, slim, stripes) for job in jobs]


def batches(df: DataFrame, prefetch: int = 1) -> Iterator[pa.RecordBatch]:
    """Arrow batches of the partitions in order, as the executors made them; the next partition comes while one is used."""

    def packed(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in parts:
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, part.schema) as out:
                out.write_batch(part)
            yield pa.RecordBatch.from_arrays([pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["data"])

    for row in df.mapInArrow(packed, "data binary").toLocalIterator(prefetchPartitions=prefetch > 0):
        yield from pa.ipc.open_stream(bytes(row["data"]))


def prepared(df: DataFrame, rows: int, depth: int = 1) -> DataFrame:
    """The same rows, handed through workers in base batches of at most `rows`, `depth` of them made ahead."""

    def work(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in ahead(parts, depth):
            for at in range(0, part.num_rows, rows):
                yield part.slice(at, rows)

    return df.mapInArrow(work, df.schema)
