"""Replay: from slim examples and stripes back to the sequences that requests were served with."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from histreplay.operators import joins, project
from histreplay.schema import DAY, HOUR
from histreplay.sources.scratch import folder

#: Stripes that the broadcast strategy sends at once; more of them go in rounds.
BROADCAST_STRIPES = 200_000
#: Files of a round's asks and stripes.
ROUND_FILES = 8
#: Width of the buckets of time in which the range strategy looks for stripes: about a lookback window.
RANGE_BUCKET = 32 * DAY
STRATEGIES = ("range", "equi", "affinity", "broadcast")


def unpack(slim: DataFrame) -> DataFrame:
    """A row for each request and pointer, with the number of logged events; requests without pointer are left out."""
    return slim.select("request_id", "user_id", "t_us", F.size("m_us").alias("mutable"), F.inline("pointers"))


def _tail(values: Column, n: Column) -> Column:
    size = F.size(values)
    return F.when(n <= 0, F.slice(values, F.lit(1), F.lit(0))).otherwise(F.slice(values, F.greatest(F.lit(1), size - n + 1).cast("int"), F.greatest(F.lit(0), n).cast("int")))


def _held(bounds: DataFrame, stripes: DataFrame, keys: list[str]) -> DataFrame:
    """The stripes that overlap each ask's [start_us, end_us], with the stripes sent to all tasks."""
    return bounds.join(F.broadcast(stripes), keys).filter((F.col("first_us") <= F.col("end_us")) & (F.col("last_us") >= F.col("start_us")))


def _in_rounds(bounds: DataFrame, stripes: DataFrame, keys: list[str], count: int) -> DataFrame:
    """As _held for more stripes than are sent at once: a round for each block of histories, and in memory one round's at a time.

    Asks and stripes are written by block, so a round reads its own block only. Blocks of histories so long that they
    still hold too many stripes are sent in several parts, each of which meets all asks of the block.
    """
    spark, root = stripes.sparkSession, f"{folder(stripes.sparkSession)}/rounds-{uuid.uuid4().hex}"
    blocks = -(-2 * count // BROADCAST_STRIPES)
    block = F.pmod(F.xxhash64(*keys), F.lit(blocks)).cast("int")
    sides = {"asks": (bounds, "request_id"), "stripes": (stripes, "stripe_no")}
    for side, (rows, own) in sides.items():
        dealt = rows.withColumn("block", block).repartition("block", F.pmod(F.xxhash64(own), F.lit(ROUND_FILES)))
        dealt.write.partitionBy("block").parquet(f"{root}/{side}")
    asks, stored = (spark.read.schema(f"{', '.join(f'`{c}` {t}' for c, t in rows.dtypes)}, block int").parquet(f"{root}/{side}") for side, (rows, _) in sides.items())
    schema = None
    for r in stored.groupBy("block").count().collect():
        wanted, held = (x.filter(F.col("block") == r["block"]).drop("block") for x in (asks, stored))
        parts = 1 if r["count"] <= BROADCAST_STRIPES else -(-2 * r["count"] // BROADCAST_STRIPES)
        for k in range(parts):
            hit = _held(wanted, held if parts == 1 else held.filter(F.pmod(F.xxhash64(*keys, "stripe_no"), F.lit(parts)) == k), keys)
            hit.write.mode("append").parquet(f"{root}/hit")
            schema = hit.schema
    for side in sides:
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{root}/{side}")
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    return spark.read.schema(schema).parquet(f"{root}/hit")


def multi_range(asks: DataFrame, stripes: DataFrame, strategy: str = "range", parallelism: int | None = None, window: int = HOUR) -> DataFrame:
    """(request_id, feature_group, stripe columns): all stripes that the asked ranges touch, in one join for all ranges.

    asks has request_id, user_id, feature_group, t_us, start_us, end_us, lo, hi. range: stripes that overlap
    [start, end]; equi: stripe numbers lo..hi, spelled out; affinity: one lookup for each user, group and window of
    time, shared by its requests; broadcast: as range, with the stripes sent to all tasks, in rounds if they are many.
    parallelism deals the stripes over so many tasks by user.
    """
    keys = ["user_id", "feature_group"]
    if parallelism:
        stripes = stripes.repartition(parallelism, "user_id")
    if strategy == "equi":
        spelled = asks.filter("lo is not null").withColumn("stripe_no", F.explode(F.sequence("lo", "hi")))
        return spelled.select("request_id", *keys, "stripe_no").join(stripes, [*keys, "stripe_no"])
    if strategy == "affinity":
        slot = F.floor(F.col("t_us") / window)
        wanted = asks.filter("lo is not null").withColumn("slot", slot)
        lookups = wanted.groupBy(*keys, "slot").agg(F.min("lo").alias("from_no"), F.max("hi").alias("to_no"))
        read = lookups.join(stripes, keys).filter((F.col("stripe_no") >= F.col("from_no")) & (F.col("stripe_no") <= F.col("to_no"))).drop("from_no", "to_no")
        own = wanted.select("request_id", *keys, "slot", "lo", "hi")
        return own.join(read, [*keys, "slot"]).filter((F.col("stripe_no") >= F.col("lo")) & (F.col("stripe_no") <= F.col("hi"))).drop("slot", "lo", "hi")
    if strategy not in ("range", "broadcast"):
        raise ValueError(f"strategy is one of {STRATEGIES}")
    least = F.coalesce("lo", F.lit(0)) if "lo" in asks.columns else F.lit(0)
    bounds = asks.select("request_id", *keys, "start_us", "end_us", least.alias("lo"))
    if strategy == "range":
        hit = joins.overlapping(bounds, stripes, keys, ("start_us", "end_us"), ("first_us", "last_us"), RANGE_BUCKET)
    else:
        count = stripes.count()
        hit = _held(bounds, stripes, keys) if count <= BROADCAST_STRIPES else _in_rounds(bounds, stripes, keys, count)
    return hit.filter(F.col("stripe_no") >= F.col("lo")).drop("start_us", "end_us", "lo")


def cut(asks: DataFrame, read: DataFrame, traits: tuple[str, ...], generation: int | None = None) -> DataFrame:
    """Joins a request's stripes in order, cuts them to [start, end] and to the needed tail: (request_id, i_*) arrays.

    Only bounds and lengths of asks are joined in; sequences are made once, here, and not shuffled again. With a
    generation, events that a later build has loaded (trait ingest_gen) don't count, whatever their time.
    """
    packed = F.sort_array(F.collect_list(F.struct("stripe_no", *[F.col(t) for t in traits])))
    joined = read.groupBy("request_id", "feature_group").agg(packed.alias("s"))
    flat = joined.select("request_id", "feature_group", *[F.flatten(F.col("s")[t]).alias(t) for t in traits])
    bounds = asks.select("request_id", "feature_group", "start_us", "end_us", "need")
    ev = F.arrays_zip(*traits)
    inside = F.filter(ev, lambda e: (e["us"] >= F.col("start_us")) & (e["us"] <= F.col("end_us")))
    if generation is not None:
        inside = F.filter(inside, lambda e: e["ingest_gen"] <= generation)
    kept = flat.join(bounds, ["request_id", "feature_group"]).withColumn("ev", _tail(inside, F.col("need")))
    return kept.select("request_id", "feature_group", *[F.col("ev")[t].alias(f"i_{t}") for t in traits])


def reconstruct(slim: DataFrame, stripes: DataFrame, length: int | None = None, strategy: str = "affinity", stripe_len: int = 8, traits: tuple[str, ...] = ("us", "event_id"), generation: int | None = None) -> DataFrame:
    """(request_id, user_id, t_us, traits): the last `length` events up to each request, oldest first, as arrays.

    Takes the pointers apart, works out which stripes each request needs, reads them in one batched join, cuts, and
    puts the logged events after them. length None is the whole window; it counts logged events too. generation is the
    build that the pointers were logged against, for tiers with late arrivals (trait ingest_gen); late events shift
    ranks, so the stripes are then found by their times (strategy range or broadcast).
    """
    asks = unpack(slim).filter("seq_len > 0")
    if generation is not None:
        if strategy not in ("range", "broadcast"):
            raise ValueError("pinned generations are replayed by range or broadcast")
        asks = asks.withColumn("need", project.need(F.col("seq_len"), F.col("mutable"), length)).filter("need > 0")
        read = multi_range(asks, project.traits(stripes, (*traits, "ingest_gen")), strategy)
        old = cut(asks, read, (*traits, "ingest_gen"), generation).drop("feature_group", "i_ingest_gen")
    else:
        if strategy in ("equi", "affinity") or length is not None:
            asks = project.spans(asks, stripes, length, stripe_len).filter("need > 0")
        else:
            asks = asks.withColumn("need", F.col("seq_len"))
        old = cut(asks, multi_range(asks, project.traits(stripes, traits), strategy), traits).drop("feature_group")
    out = slim.join(old, "request_id", "left")
    parts = {t: F.when(F.col(f"i_{t}").isNull(), F.col(f"m_{t}")).otherwise(F.concat(f"i_{t}", f"m_{t}")) for t in traits}
    if length is not None:
        parts = {t: _tail(c, F.lit(length)) for t, c in parts.items()}
    return out.select("request_id", "user_id", "t_us", *[c.alias(t) for t, c in parts.items()])


def interleave(slim: DataFrame, stripes: DataFrame, length: int | None = None, stripe_len: int = 8) -> DataFrame:
    """Replay from pointers per group: the groups' events merged by time, then cut to the last `length`."""
    asks = unpack(slim).filter("seq_len > 0")
    asks = project.spans(asks, stripes, length, stripe_len).filter("need > 0")
    traits = ("us", "event_id")
    old = cut(asks, multi_range(asks, project.traits(stripes, traits), "equi"), traits)
    merged = old.groupBy("request_id").agg(F.sort_array(F.flatten(F.collect_list(F.arrays_zip(F.col("i_us").alias("us"), F.col("i_event_id").alias("event_id"))))).alias("ev"))
    out = slim.join(merged, "request_id", "left")
    ev = F.concat(F.coalesce("ev", F.array().cast("array<struct<us:bigint,event_id:bigint>>")), F.arrays_zip(F.col("m_us").alias("us"), F.col("m_event_id").alias("event_id")))
    if length is not None:
        ev = _tail(ev, F.lit(length))
    return out.select("request_id", "user_id", "t_us", ev.alias("ev")).select("request_id", "user_id", "t_us", F.col("ev.us").alias("us"), F.col("ev.event_id").alias("event_id"))


def index_join(probe: DataFrame, build: DataFrame, how: str = "merge") -> DataFrame:
    """Probe rows with the stripes of their user and stripe number; no shuffle where both are bucketed by user."""
    return probe.join(build.hint(how), ["user_id", "feature_group", "stripe_no"])


def scrub_logged(slim: DataFrame, items: DataFrame) -> DataFrame:
    """Takes the events of deleted items out of the logged arrays too, by an anti join of the events, however many are deleted."""
    cols = [c for c in slim.columns if c.startswith("m_")]
    gone = items.select(F.col(items.columns[0]).cast(dict(slim.select(F.explode("m_item_id").alias("x")).dtypes)["x"]).alias("m_item_id")).distinct()
    events = slim.select("request_id", F.posexplode(F.arrays_zip(*cols)).alias("k", "e")).select("request_id", "k", "e.*")
    left = events.join(gone, "m_item_id", "left_anti").groupBy("request_id").agg(F.sort_array(F.collect_list(F.struct("k", *cols))).alias("ev"))
    kept = slim.select(*[c for c in slim.columns if c not in cols]).join(left, "request_id", "left")
    parts = [F.coalesce(F.col("ev")[c], F.array()).cast(slim.schema[c].dataType).alias(c) for c in cols]
    return kept.select("*", *parts).select(*slim.columns)
