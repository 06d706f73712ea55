"""The immutable tier's organisation: stripes of events with one array for each trait."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from histreplay.schema import EVENT_COLUMNS, ONE_GROUP, STRIPE_INDEX, LayoutSpec


def number(immutable: DataFrame, spec: LayoutSpec = LayoutSpec()) -> DataFrame:
    """Adds each event's rank in its (user, group) history and its stripe number."""
    hist = immutable if spec.per_group else immutable.withColumn("feature_group", F.lit(ONE_GROUP))
    rank = F.row_number().over(Window.partitionBy("user_id", "feature_group").orderBy("us", "event_id")) - 1
    ranked = hist.withColumn("rank", rank.cast("long"))
    stripe = F.floor(F.col("rank") / spec.stripe_len) if spec.mode == "count" else F.floor(F.col("us") / spec.span)
    return ranked.withColumn("stripe_no", stripe.cast("long"))


def build(immutable: DataFrame, spec: LayoutSpec = LayoutSpec(), traits: tuple[str, ...] = EVENT_COLUMNS) -> DataFrame:
    """Stripes: key, bounds, n_events, events_before (rank of the first event), and parallel trait arrays.

    One shuffle by user and group serves ranking, cutting and collecting. A row is bounded by the stripe's length.
    """
    rows = number(immutable, spec)
    rest = [t for t in traits if t not in ("us", "event_id")]
    packed = F.sort_array(F.collect_list(F.struct("us", "event_id", *rest))).alias("ev")
    cut = rows.groupBy("user_id", "feature_group", "stripe_no").agg(F.min("us").alias("first_us"), F.max("us").alias("last_us"), F.count("*").cast("int").alias("n_events"), F.min("rank").alias("events_before"), packed)
    return cut.select(*STRIPE_INDEX, *[F.col("ev")[t].alias(t) for t in traits])


def index(stripes: DataFrame) -> DataFrame:
    """The narrow columns: enough to resolve which stripes a pointer needs, without reading an array."""
    return stripes.select(*STRIPE_INDEX)


def explode(stripes: DataFrame, traits: tuple[str, ...] = EVENT_COLUMNS) -> DataFrame:
    """Events again, one row each."""
    return stripes.select("user_id", "feature_group", F.inline(F.arrays_zip(*traits)))
