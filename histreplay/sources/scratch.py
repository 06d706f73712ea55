"""The folder for intermediate files: shared on a cluster, local only in tests."""

from __future__ import annotations

import tempfile

from pyspark.sql import SparkSession

_local: str | None = None


def folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; where that is unset, a temporary folder in local mode only."""
    global _local
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir is unset: the executors share no folder with the driver")
    if _local is None:
        _local = f"file://{tempfile.mkdtemp(prefix='histreplay-')}"
    return _local
