"""Projection by length, group and trait, handed to the stripe scan."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from histreplay.schema import ONE_GROUP, STRIPE_INDEX, TenantSpec


def need(seq_len: Column, mutable: Column, length: int | None) -> Column:
    """Events that a sequence of `length` takes from the immutable part, after the logged ones."""
    if length is None:
        return seq_len.cast("long")
    return F.least(seq_len, F.greatest(F.lit(0), F.lit(length) - mutable)).cast("long")


def stripe_span(window_rank: Column, seq_len: Column, needed: Column, stripe_len: int) -> tuple[Column, Column]:
    """(lo, hi) stripe numbers of the last `needed` events of a window that starts at rank window_rank; null if none."""
    lo = F.floor((window_rank + seq_len - needed) / stripe_len)
    hi = F.floor((window_rank + seq_len - 1) / stripe_len)
    some = needed > 0
    return F.when(some, lo).cast("long"), F.when(some, hi).cast("long")


def groups(stripes: DataFrame, wanted: tuple[str, ...] | None) -> DataFrame:
    return stripes if wanted is None else stripes.filter(F.col("feature_group").isin(*wanted))


def traits(stripes: DataFrame, wanted: tuple[str, ...]) -> DataFrame:
    """Only the wanted arrays; the others' columns are not read from the files."""
    return stripes.select(*STRIPE_INDEX, *wanted)


def with_ranks(pointers: DataFrame, index: DataFrame) -> DataFrame:
    """Adds window_rank: the rank, in this build, of each pointer's first event. Read from the narrow columns alone.

    Pointers and stripes lie on one time line for each history, from late to early: the stripe that holds a start is the
    last one that ended at it or after. One shuffle and one pass, whatever the number of stripes; events of the stripe
    before the start are counted from its times, so ties at the bounds come out right.
    """
    keys = ["user_id", "feature_group"]
    asks = pointers.select("request_id", *keys, F.col("start_us").alias("t"), F.lit(0).alias("side"), F.lit(0).cast("long").alias("no"))
    held = index.select(*keys, F.col("last_us").alias("t"), F.lit(1).alias("side"), F.col("stripe_no").alias("no"), F.struct("events_before", "us").alias("stripe"))
    line = Window.partitionBy(*keys).orderBy(F.col("t").desc(), F.col("side").desc(), F.col("no").desc()).rowsBetween(Window.unboundedPreceding, 0)
    both = asks.unionByName(held, allowMissingColumns=True).withColumn("at", F.last("stripe", ignorenulls=True).over(line)).filter("side = 0")
    rank = F.col("at.events_before") + F.size(F.filter("at.us", lambda x: x < F.col("t")))
    return pointers.join(both.select("request_id", "feature_group", rank.alias("window_rank")), ["request_id", "feature_group"], "left")


def spans(pointers: DataFrame, stripes: DataFrame, length: int | None, stripe_len: int) -> DataFrame:
    """Pointers with need, lo and hi. pointers has request_id, user_id, feature_group, bounds, seq_len and mutable."""
    ranked = with_ranks(pointers.filter("seq_len > 0"), stripes)
    ranked = ranked.withColumn("need", need(F.col("seq_len"), F.col("mutable"), length))
    lo, hi = stripe_span(F.col("window_rank"), F.col("seq_len"), F.col("need"), stripe_len)
    return ranked.withColumns({"lo": lo, "hi": hi})


def apply(stripes: DataFrame, spec: TenantSpec, per_group: bool = False) -> DataFrame:
    """The stripe columns and groups that a tenant reads; lengths come in by spans()."""
    kept = groups(stripes, spec.groups) if per_group else stripes.filter(F.col("feature_group").isin(ONE_GROUP, *(spec.groups or ())))
    return traits(kept, tuple(dict.fromkeys(("us", "event_id", *spec.traits))))
