"""The stored immutable tier: stripes with encoded trait columns, in buckets of users, read by what a job wants."""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from histreplay.functions import codec
from histreplay.schema import STRIPE_INDEX


def plan(hist: DataFrame, traits: tuple[str, ...]) -> dict[str, str]:
    """Codec by trait, from one pass over the events: types, distinct values, and whether a trait rises along histories."""
    kinds = dict(hist.select(*traits).dtypes)
    line = Window.partitionBy("user_id").orderBy("us", "event_id")
    whole = [t for t in traits if kinds[t] in ("bigint", "int")]
    steps = hist.select(*traits, *[(F.col(t) >= F.lag(t).over(line)).alias(f"up_{t}") for t in whole])
    row = steps.agg(F.count("*").alias("rows"), *[F.approx_count_distinct(t).alias(f"n_{t}") for t in traits], *[F.coalesce(F.avg(F.col(f"up_{t}").cast("int")), F.lit(0.0)).alias(f"share_{t}") for t in whole]).first()
    return codec.plan({t: {"type": kinds[t], "distinct": row[f"n_{t}"] if kinds[t] == "string" else row["rows"], "rows": row["rows"], "ordered": t in whole and row[f"share_{t}"] > 0.99} for t in traits}, dictionary_share=0.01)


def encode(stripes: DataFrame, codecs: dict[str, str]) -> DataFrame:
    """Stripes with the columns of each trait's codec in place of its array."""
    cols: list[Column] = []
    for t, kind in codecs.items():
        if kind == "delta":
            cols.append(codec.delta_encode(F.col(t).cast("array<bigint>")).alias(f"{t}_delta"))
        elif kind == "dictionary":
            words, codes = codec.dict_encode(F.col(t))
            cols += [words.alias(f"{t}_words"), codes.alias(f"{t}_codes")]
        elif kind == "bitmap":
            cols.append(codec.bitmap_encode(F.col(t)).alias(f"{t}_bits"))
        else:
            cols.append(F.col(t))
    return stripes.select(*STRIPE_INDEX, *cols)


def decode(table: DataFrame, codecs: dict[str, str], traits: tuple[str, ...], types: dict[str, str]) -> DataFrame:
    """Stripes again, with the wanted traits alone: the columns of others are not read."""
    cols: list[Column] = []
    for t in traits:
        kind = codecs[t]
        if kind == "delta":
            cols.append(codec.delta_decode(F.col(f"{t}_delta")).cast(types[t]).alias(t))
        elif kind == "dictionary":
            cols.append(codec.dict_decode(F.col(f"{t}_words"), F.col(f"{t}_codes")).cast(types[t]).alias(t))
        elif kind == "bitmap":
            cols.append(codec.bitmap_decode(F.col(f"{t}_bits"), F.col("n_events")).alias(t))
        else:
            cols.append(F.col(t))
    return table.select(*STRIPE_INDEX, *cols)


def describe(codecs: dict[str, str], stripes: DataFrame) -> str:
    """What a reader must know of a stored generation, as JSON."""
    kinds = dict(stripes.dtypes)
    return json.dumps({"codecs": codecs, "types": {t: kinds[t] for t in codecs}})


def opened(table: DataFrame, description: str, traits: tuple[str, ...] | None = None) -> DataFrame:
    own = json.loads(description)
    return decode(table, own["codecs"], tuple(own["codecs"]) if traits is None else traits, own["types"])
