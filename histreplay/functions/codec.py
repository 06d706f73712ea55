"""Trait-aware encodings of arrays, and their sizes in bits."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD = 64


def delta_encode(values: Column) -> Column:
    """First value, then differences."""
    return F.transform(values, lambda x, k: F.when(k == 0, x).otherwise(x - F.get(values, k - 1)))


def delta_decode(deltas: Column) -> Column:
    empty = F.array().cast("array<bigint>")
    return F.aggregate(deltas, empty, lambda out, d: F.array_append(out, F.coalesce(F.get(out, F.size(out) - 1), F.lit(0)) + d))


def bitmap_encode(flags: Column) -> Column:
    """Words of 64 flags, lowest bit first."""
    words = F.when(F.size(flags) > 0, F.sequence(F.lit(0), ((F.size(flags) - 1) / WORD).cast("int"))).otherwise(F.array().cast("array<int>"))

    def word(w: Column) -> Column:
        own = F.slice(flags, w * WORD + 1, F.lit(WORD))
        bits = F.transform(own, lambda f, k: F.when(f, F.call_function("shiftleft", F.lit(1).cast("long"), k)).otherwise(F.lit(0).cast("long")))
        return F.aggregate(bits, F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(b))

    return F.transform(words, word)


def bitmap_decode(words: Column, n: Column) -> Column:
    places = F.when(n > 0, F.sequence(F.lit(0), (n - 1).cast("int"))).otherwise(F.array().cast("array<int>"))
    return F.transform(places, lambda k: F.call_function("shiftrightunsigned", F.get(words, (k / WORD).cast("int")), (k % WORD).cast("int")).bitwiseAND(F.lit(1).cast("long")) == 1)


def dict_encode(values: Column) -> tuple[Column, Column]:
    """(sorted distinct values, codes from 0)."""
    words = F.array_sort(F.array_distinct(values))
    return words, F.transform(values, lambda v: (F.array_position(words, v) - 1).cast("int"))


def dict_decode(words: Column, codes: Column) -> Column:
    return F.transform(codes, lambda c: F.get(words, c))


def bits_for(n: Column) -> Column:
    """Bits that tell n values apart, at least 1."""
    return F.greatest(F.lit(1), F.ceil(F.log2(F.greatest(n.cast("double"), F.lit(1.0))))).cast("long")


def plan(stats: dict[str, dict], dictionary_share: float = 0.5) -> dict[str, str]:
    """Codec by trait from {trait: {type, distinct, rows, set_share}}: bitmaps for flags, differences for whole numbers

    that mostly rise, dictionaries for traits with few values, else plain.
    """
    out = {}
    for trait, s in stats.items():
        if s.get("type") == "boolean":
            out[trait] = "bitmap"
        elif s.get("type") in ("long", "bigint", "int") and s.get("ordered"):
            out[trait] = "delta"
        elif s.get("rows") and s["distinct"] <= dictionary_share * s["rows"]:
            out[trait] = "dictionary"
        else:
            out[trait] = "plain"
    return out


def trait_stats(hist: DataFrame, traits: dict[str, str]) -> dict[str, dict]:
    """One pass of statistics for plan(): approximate distinct counts and whether a trait rises along each history."""
    row = hist.agg(F.count("*").alias("rows"), *[F.approx_count_distinct(t).alias(t) for t in traits]).first()
    return {t: {"type": kind, "distinct": row[t], "rows": row["rows"], "ordered": t in ("us", "event_id")} for t, kind in traits.items()}


def size_report(stripes: DataFrame) -> DataFrame:
    """(trait, plain_bits, encoded_bits) over all stripes.

    us: 64-bit base and differences of the width that the largest needs; event_type: codes of the stripe's dictionary
    plus 64 bits for each entry; is_purchase: one bit an event against 8; value: as is.
    """
    gap = F.array_max(F.transform("us", lambda x, k: F.when(k == 0, F.lit(0).cast("long")).otherwise(x - F.get(F.col("us"), k - 1))))
    n = F.col("n_events").cast("long")
    kinds = F.size(F.array_distinct("event_type")).cast("long")
    rows = F.array(
        F.struct(F.lit("us").alias("trait"), (64 * n).alias("plain"), (64 + (n - 1) * bits_for(gap + 1)).alias("encoded")),
        F.struct(F.lit("event_type").alias("trait"), (64 * n).alias("plain"), (64 * kinds + n * bits_for(kinds)).alias("encoded")),
        F.struct(F.lit("is_purchase").alias("trait"), (8 * n).alias("plain"), (64 * F.ceil(n / WORD)).cast("long").alias("encoded")),
        F.struct(F.lit("value").alias("trait"), (64 * n).alias("plain"), (64 * n).alias("encoded")),
    )
    return stripes.select(F.explode(rows).alias("x")).groupBy("x.trait").agg(F.sum("x.plain").alias("plain_bits"), F.sum("x.encoded").alias("encoded_bits"))
