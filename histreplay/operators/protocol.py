"""The split of a history at a cutoff, and what is logged with each request."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from histreplay.functions.digest import additive, event_hash, ordered
from histreplay.operators.history import sequences, window_events
from histreplay.schema import DAY, EVENT_COLUMNS, ONE_GROUP, PointerSpec


def cutoff_of(t: Column, cadence: int = DAY, lag: int = 0) -> Column:
    """End of the immutable part that a request at t can see."""
    return (F.floor((t - lag) / cadence) * cadence).cast("long")


def bifurcate(hist: DataFrame, cutoff_us: int) -> tuple[DataFrame, DataFrame]:
    """(mutable, immutable): no gap, no overlap."""
    return hist.filter(F.col("us") >= cutoff_us), hist.filter(F.col("us") < cutoff_us)


def _grouped(hist: DataFrame, spec: PointerSpec) -> DataFrame:
    return hist if spec.per_group else hist.withColumn("feature_group", F.lit(ONE_GROUP))


def pointers(requests: DataFrame, hist: DataFrame, spec: PointerSpec = PointerSpec()) -> DataFrame:
    """(request_id, user_id, t_us, feature_group, start_us, end_us, seq_len, digest), one row for each group.

    Events are first reduced to a row for each user, group and period; requests then look at the periods of their
    window in one window function. So no request touches its events, and one shuffle by user serves all. An empty
    immutable part has seq_len 0 and null bounds. digest: additive (a sum over periods), ordered (MD5 over the events,
    which must be read for it) or none.
    """
    hist = _grouped(hist, spec)
    period = F.floor(F.col("us") / spec.cadence)
    daily = hist.groupBy("user_id", "feature_group", period.alias("period")).agg(F.min("us").alias("first"), F.max("us").alias("last"), F.count("*").alias("cnt"), F.sum(event_hash(F.col("us"), F.col("event_id"))).alias("hash"))
    groups = sorted({"dense", "sparse", "ops"}) if spec.per_group else [ONE_GROUP]
    asks = requests.select("user_id", F.explode(F.array(*[F.lit(g) for g in groups])).alias("feature_group"), (cutoff_of(F.col("t_us"), spec.cadence, spec.lag) / spec.cadence).cast("long").alias("period"), "request_id", "t_us")
    both = daily.unionByName(asks, allowMissingColumns=True)
    frame = Window.partitionBy("user_id", "feature_group").orderBy("period").rangeBetween(-(spec.lookback_days - 1), -1)
    found = both.select("request_id", "user_id", "t_us", "feature_group", F.min("first").over(frame).alias("start_us"), F.max("last").over(frame).alias("end_us"), F.coalesce(F.sum("cnt").over(frame), F.lit(0)).alias("seq_len"), F.coalesce(F.sum("hash").over(frame), F.lit(0)).alias("hash")).filter("request_id is not null")
    if spec.digest == "additive":
        return found.withColumn("digest", additive(F.col("hash")).cast("string")).drop("hash")
    found = found.drop("hash")
    if spec.digest is None:
        return found.withColumn("digest", F.lit(None).cast("string"))
    rows = window_events(requests, hist, spec.lookback_days, spec.cadence, spec.lag).filter("us < cutoff_us")
    seq = sequences(rows, ["request_id", "feature_group"], ("us", "event_id")).select("request_id", "feature_group", ordered(F.col("us"), F.col("event_id")).alias("digest"))
    return found.join(seq, ["request_id", "feature_group"], "left")


def mutable_arrays(requests: DataFrame, hist: DataFrame, spec: PointerSpec = PointerSpec(), traits: tuple[str, ...] = EVENT_COLUMNS) -> DataFrame:
    """(request_id, m_*): the events in [cutoff, t] that are logged physically, as parallel arrays."""
    asks = requests.withColumn("cutoff_us", cutoff_of(F.col("t_us"), spec.cadence, spec.lag)).withColumn("period", (F.col("cutoff_us") / spec.cadence).cast("long"))
    span = -(-spec.lag // spec.cadence) + 1
    asks = asks.withColumn("period", F.explode(F.sequence(F.col("period"), F.col("period") + span)))
    recent = hist.withColumn("period", F.floor(F.col("us") / spec.cadence))
    rows = asks.join(recent, ["user_id", "period"]).filter((F.col("us") >= F.col("cutoff_us")) & (F.col("us") <= F.col("t_us")))
    return sequences(rows, ["request_id"], traits).select("request_id", *[F.col(t).alias(f"m_{t}") for t in traits])


def snapshot(requests: DataFrame, hist: DataFrame, spec: PointerSpec = PointerSpec(), traits: tuple[str, ...] = EVENT_COLUMNS) -> DataFrame:
    """The slim example: request, mutable arrays, and an array of pointers (one for each group)."""
    fields = ("feature_group", "start_us", "end_us", "seq_len", "digest")
    logged = pointers(requests, hist, spec).filter("seq_len > 0").groupBy("request_id").agg(F.sort_array(F.collect_list(F.struct(*fields))).alias("pointers"))
    recent = mutable_arrays(requests, hist, spec, traits)
    slim = requests.join(recent, "request_id", "left").join(logged, "request_id", "left")
    kinds = {"us": "bigint", "event_id": "bigint", "event_type": "string", "value": "double", "item_id": "int"}
    filled = {f"m_{t}": F.coalesce(f"m_{t}", F.array().cast(f"array<{kinds[t]}>")) for t in traits}
    return slim.withColumns(filled | {"pointers": F.coalesce("pointers", F.array().cast("array<struct<feature_group:string,start_us:bigint,end_us:bigint,seq_len:bigint,digest:string>>"))})


def retention_gaps(hist: DataFrame, now_us: int, retention: int, published_us: int) -> DataFrame:
    """Events up to now that are in no tier: not in the published build (before published_us), no longer in the mutable tier."""
    return hist.filter((F.col("us") >= published_us) & (F.col("us") < now_us - retention) & (F.col("us") <= now_us))


def check_retention(retention: int, cadence: int = DAY, lag: int = 0) -> bool:
    """Mutable retention has to cover a build cycle and its lag."""
    if retention < cadence + lag:
        raise ValueError(f"retention {retention} is shorter than cadence {cadence} plus lag {lag}: events fall between the tiers")
    return True
