"""A training corpus from raw documents: language id, exact dedup, near dedup, mixing, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from histreplay.llm import exact_dedup, lang_id, mixing, near_dedup, packing
from histreplay.llm.common import give_back_heaps, release, stored, written
from histreplay.llm.registry import SOURCE_WEIGHTS, vocabulary


def identify_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops texts of which no language can be told: null, empty, without a letter, or far below the usual score of their language.

    Equal texts fare alike, and so do rows that repeat. An empty table stays empty.
    """
    return lang_id.keep_identified(docs)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document of the largest id of each group of equal texts; null texts equal empty ones, null ids lose to others.

    Rows that repeat id and text leave one row. An empty table stays empty.
    """
    return exact_dedup.drop_exact_duplicates(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document of the smallest id of each group of near duplicates; texts without a word, and null ids, stay.

    Rows that repeat an id go or stay together. An empty table stays empty.
    """
    give_back_heaps(spark)
    return near_dedup.drop_near_duplicates(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats, cuts and drops documents so that sources come near their target shares; texts without a word are never taken.

    A null source is a source of its own; ties go by id, size and text. An empty table stays empty.
    """
    return mixing.mixed_documents(docs, SOURCE_WEIGHTS)


def pack_windows(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in training windows, with their token ids, as op9 packs them; null texts count as empty.

    Rows that repeat are packed each. An empty table gives no piece.
    """
    give_back_heaps(spark)
    return packing.pack(docs, vocabulary("word_bpe_49k.json")).withColumnRenamed("id", "doc_id")


STAGES = [
    ("language_id", identify_languages),
    ("exact_dedup", drop_exact_copies),
    ("near_dedup", drop_near_copies),
    ("mix_sources", mix_sources),
    ("pack", pack_windows),
]

#: Hypervectors, MinHash and tokenizers have no SQL twin; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies all stages to the documents table; each one's rows are written and read again for the next.

    What a stage wrote on its way is deleted once its rows are written, and so are the rows of the stage before.
    """
    docs, since = spark.read.parquet(f"{sf_dir}/documents.parquet"), written()
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
        release(spark, since, keep=1)
    return STAGES[-1][1](spark, docs, sf_dir)
