"""Mixing sources to target weights by Efraimidis-Spirakis sampling."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from histreplay.llm.common import BROADCAST_ROWS, bucket_of, range_bounds, release, shuffle_width, stored, unused, with_prefix_sums, written

WORD = r"[^\x20\x09-\x0D]+"


def n_words(text: Column) -> Column:
    return F.coalesce(F.size(F.array_remove(F.split(text, r"[\x20\x09-\x0D]+"), "")), F.lit(0)).cast("long")


def quality_weight(text: Column, size: Column) -> Column:
    """Weight in [0.1, 1]: falls with the symbols per word of a document; 1 for plain prose."""
    marks = F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))
    return F.coalesce(F.greatest(F.lit(0.1), F.lit(1.0) - marks / F.greatest(size, F.lit(1))), F.lit(1.0))


def uniform(*keys: Column, seed: int) -> Column:
    """A number in (0, 1) that the keys and the seed decide, the same on every engine: 52 bits of an MD5."""
    text = F.concat_ws(":", *[F.coalesce(k.cast("string"), F.lit("-")) for k in keys], F.lit(str(seed)))
    return (F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)


def weights_in_order(sources: Sequence[str | None], pattern: Sequence[float]) -> dict[str | None, float]:
    """Weights dealt round-robin to the sources by code point, null last."""
    named = sorted((s for s in sources if s is not None), key=lambda s: [ord(c) for c in s])
    return {s: float(pattern[k % len(pattern)]) for k, s in enumerate([*named, *([None] if None in sources else [])])}


def targets(sizes: dict[str | None, int], weights: dict[str | None, float], total: float, most: float) -> dict[str | None, float]:
    """Splits total by weight; no share passes most * size, and what is cut off goes to the others by weight."""
    out = {s: 0.0 for s in sizes}
    open_, left = {s for s, n in sizes.items() if n > 0 and weights[s] > 0}, float(total)
    while open_:
        unit = left / sum(weights[s] for s in open_)
        full = {s for s in open_ if weights[s] * unit > most * sizes[s]}
        if not full:
            return out | {s: weights[s] * unit for s in open_}
        for s in full:
            out[s] = most * float(sizes[s])
        left -= sum(out[s] for s in full)
        open_ -= full
    return out


def mix(docs: DataFrame, weights: Sequence[float] | dict, most: float = 3.0, share: float = 1.0, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weight: Column | None = None, seed: int = 11) -> DataFrame:
    """(id, source, size, source_size, target, epochs, part, taken, key, text_hash), a row for each document.

    size counts words. Each source's target is its share by weight of `share` of all words, at most `most` times the
    source's own. All of a source is taken target / source_size times, rounded down (epochs); the rest of the budget
    goes to documents in the order of exponential keys, -ln(u) / quality weight, summed up by size: part is what the
    last pass takes of a document, the whole or nothing, or its leading words for the one document where the budget
    ends. taken = epochs * size + part. u is a hash of id and seed, so that reruns agree; ties go by size, then a hash of the text.

    One row for each source reaches the driver, so sources are the components of a mixture, not keys of documents.
    Null texts have size 0 and are never taken; null is a source of its own, last in order; rows that repeat an id
    count each. An empty table gives an empty result.
    """
    size = n_words(F.col(text_col))
    w = quality_weight(F.col(text_col), size) if weight is None else weight
    key = -F.ln(uniform(F.col(id_col), seed=seed)) / w
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(source_col).cast("string").alias("source"), size.alias("size"), key.alias("key"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("text_hash"))
    rows = stored(rows, "keys")
    sizes = {r["source"]: int(r["n"] or 0) for r in rows.groupBy("source").agg(F.sum("size").alias("n")).collect()}
    weights = weights if isinstance(weights, dict) else weights_in_order(list(sizes), weights)
    goal = targets(sizes, weights, share * sum(sizes.values()), most)
    kind = T.StructType([T.StructField("__s", T.StringType()), T.StructField("source_size", T.LongType()), T.StructField("target", T.DoubleType()), T.StructField("epochs", T.LongType()), T.StructField("budget", T.LongType())])
    plan = []
    for s, n in sizes.items():
        epochs = int(goal[s] // n) if n else 0
        plan.append((s, n, goal[s], epochs, math.floor(goal[s] - epochs * n + 0.5)))
    table = rows.sparkSession.createDataFrame(plan, kind)
    bounds = range_bounds(rows, "key", shuffle_width(rows.sparkSession))
    placed = rows.withColumn("bucket", bucket_of(F.col("key"), bounds))
    summed = with_prefix_sums(placed, ["source"], "bucket", [F.col("key"), F.col("id"), F.col("size"), F.col("text_hash")], {"size": "before"})
    joined = summed.join(F.broadcast(table), F.col("source").eqNullSafe(F.col("__s")))
    part = F.greatest(F.lit(0), F.least(F.col("size"), F.col("budget") - F.col("before"))).cast("long")
    return joined.withColumn("part", part).select("id", "source", "size", "source_size", "target", "epochs", "part", (F.col("epochs") * F.col("size") + F.col("part")).alias("taken"), "key", "text_hash")


def leading_words(text: Column, words: Column) -> Column:
    """The text up to the end of its first `words` words."""
    every = F.regexp_extract_all(text, F.lit(r"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+"), F.lit(0))
    return F.array_join(F.slice(every, F.lit(1), words.cast("int")), "")


def mixed_documents(docs: DataFrame, weights: Sequence[float] | dict, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **how) -> DataFrame:
    """The documents as the mix takes them: one row for each time a document is taken whole, and one for a part.

    Rows that repeat id, source and text are taken as often as they are planned all together; where their other columns
    differ, which of the rows is repeated is open. Texts are shuffled only where the plan, a row of four numbers for
    each document taken, is too long to broadcast. Null texts are never taken; an empty table gives an empty result.
    """
    since = written()
    taken = mix(docs, weights, id_col=id_col, text_col=text_col, source_col=source_col, **how)
    source = lambda c: F.coalesce(F.concat(F.lit("s"), F.col(c).cast("string")), F.lit("-"))
    key, whole, cut, again, k = unused(docs.columns, "key", "whole", "cut", "again", "k")
    planned = taken.filter("size > 0").groupBy("id", F.xxhash64(source("source"), "text_hash").alias(key), "size").agg(F.sum("epochs").alias("epochs"), F.sum("part").alias("part"), F.count("*").alias("n"))
    passes = (F.col("epochs") + F.floor(F.col("part") / F.col("size"))).cast("int")
    plan = planned.filter("epochs + part > 0").select(F.col("id").alias(f"{key}_id"), F.col(key).alias(f"{key}_of"), passes.alias(whole), (F.col("part") % F.col("size")).cast("int").alias(cut), (F.col("n") > 1).alias(again))
    plan = stored(plan, "taken")
    release(docs.sparkSession, since, keep=1)
    keyed = docs.withColumn(key, F.xxhash64(source(source_col), F.xxhash64(F.coalesce(F.col(text_col), F.lit("")))))
    same = keyed[id_col].cast("long").eqNullSafe(plan[f"{key}_id"]) & (keyed[key] == plan[f"{key}_of"])
    joined = keyed.join(F.broadcast(plan) if plan.count() <= BROADCAST_ROWS else plan, same).drop(f"{key}_id", f"{key}_of")
    if plan.filter(again).limit(1).count():
        joined = joined.filter(~F.col(again)).unionByName(joined.filter(again).dropDuplicates([id_col, key]))
    times = F.col(whole) + (F.col(cut) > 0).cast("int")
    copies = joined.withColumn(k, F.explode(F.sequence(F.lit(1), times)))
    text = F.when(F.col(k) > F.col(whole), leading_words(F.col(text_col), F.col(cut))).otherwise(F.col(text_col))
    return copies.withColumn(text_col, text).select(*docs.columns)
