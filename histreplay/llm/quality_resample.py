"""Importance resampling: hashed n-gram models of target and raw text, and a Gumbel top-k draw by their ratio."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.llm.common import bucket_of, range_bounds, ship, shuffle_width, small_batches, stored, tidied, with_prefix_sums
from histreplay.llm.mixing import uniform
from histreplay.llm.textbytes import slices, windows, word_hashes, word_spans


@dataclass(frozen=True)
class ResampleSpec:
    """buckets: of hashed words and word pairs; share: of the documents to draw; target_rows: the most labelled rows

    that the target model is learned from, the first by a hash of the id; smooth: added to each bucket's count.
    """

    buckets: int = 10_000
    share: float = 0.9
    target_rows: int = 200_000
    smooth: float = 1.0
    seed: int = 13


def _grams(data: np.ndarray, off: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of each word and word pair in order of place, and its document."""
    start, end, at = word_spans(data, off)
    h = word_hashes(data, start, end, True)
    doc = np.repeat(np.arange(len(off) - 1), np.diff(at))
    pairs = windows(h, 2)
    inside = doc[1:] == doc[:-1]
    return (np.concatenate([h, pairs[inside]]) % np.uint64(buckets)).astype(np.int64), np.concatenate([doc, doc[1:][inside]])


def learn(docs: DataFrame, labels: DataFrame, spec: ResampleSpec = ResampleSpec(), id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> np.ndarray:
    """Log ratio of target to raw chance for each bucket. Raw counts are over all documents.

    Tasks hand on two counts for each bucket, and so many numbers reach the driver. Without target documents all
    ratios are 0.
    """
    ship(docs.sparkSession)
    chosen = labels.groupBy(F.col(id_col).alias("id")).agg(F.min(label_col).alias("good")).filter("good = 1 and id is not null")
    chosen = chosen.orderBy(F.xxhash64("id"), "id").limit(spec.target_rows).select(F.col("id").alias("__id"))
    rows = docs.select(id_col, text_col).join(F.broadcast(chosen), F.col(id_col) == F.col("__id"), "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        raw, target = np.zeros(spec.buckets, np.int64), np.zeros(spec.buckets, np.int64)
        for batch in batches:
            good = np.array(batch.column(0).to_pylist(), bool)
            for first, data, off in slices(batch.column(1)):
                bucket, doc = _grams(data, off, spec.buckets)
                raw += np.bincount(bucket, minlength=spec.buckets)
                target += np.bincount(bucket[good[first + doc]], minlength=spec.buckets)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(spec.buckets)), pa.array(raw), pa.array(target)], ["k", "raw", "target"])

    counts = rows.select(F.col("__id").isNotNull().alias("good"), F.col(text_col).alias("text")).mapInArrow(tidied(run), "k long, raw long, target long")
    raw, target = np.zeros(spec.buckets), np.zeros(spec.buckets)
    with small_batches(docs.sparkSession):
        for r in counts.groupBy("k").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).collect():
            raw[r["k"]], target[r["k"]] = r["raw"], r["target"]
    if not target.any():
        return np.zeros(spec.buckets)
    logs = [np.log(x + spec.smooth) - np.log(x.sum() + spec.smooth * spec.buckets) for x in (target, raw)]
    return logs[0] - logs[1]


def weigh(docs: DataFrame, ratios: np.ndarray, spec: ResampleSpec = ResampleSpec(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_grams, log_ratio): the sum of the log ratios of a text's n-grams, which is the log of target over raw

    chance of the text; 0 for a text without words.
    """
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, data, off in slices(batch.column(1)):
                bucket, doc = _grams(data, off, spec.buckets)
                n = np.bincount(doc, minlength=len(off) - 1)
                total = np.bincount(doc, ratios[bucket], minlength=len(off) - 1)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, len(off) - 1), pa.array(n), pa.array(total, pa.float64())], ["id", "n_grams", "log_ratio"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(tidied(run), "id long, n_grams long, log_ratio double")


def resample(docs: DataFrame, labels: DataFrame, spec: ResampleSpec = ResampleSpec(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_grams, log_ratio, key, rank, kept), a row for each document.

    key = log_ratio + Gumbel noise drawn from a hash of the id; the documents with the k largest keys are a draw of k
    without replacement by weight exp(log_ratio), the ratio of the two models, k = round(share * documents). rank counts from 0;
    ties go by id. Texts without words (null too) have their noise minus 1e9 as key: drawn last, in random order, so
    that many of them are many keys. Repeated rows rank each. An empty table gives an empty result.
    """
    ratios = learn(docs, labels, spec, id_col, text_col)
    noise = -F.ln(-F.ln(uniform(F.col("id"), seed=spec.seed)))
    key = F.when(F.col("n_grams") == 0, noise - 1e9).otherwise(F.col("log_ratio") + noise)
    rows = stored(weigh(docs, ratios, spec, id_col, text_col).withColumn("key", key), "weights")
    n = rows.count()
    placed = rows.withColumns({"down": -F.col("key"), "one": F.lit(1).cast("long")})
    placed = placed.withColumn("bucket", bucket_of(F.col("down"), range_bounds(placed, "down", shuffle_width(docs.sparkSession))))
    ranked = with_prefix_sums(placed, [], "bucket", [F.col("down"), F.col("id"), F.col("n_grams")], {"one": "rank"})
    return ranked.select("id", "n_grams", "log_ratio", "key", "rank", (F.col("rank") < round(spec.share * n)).alias("kept"))
