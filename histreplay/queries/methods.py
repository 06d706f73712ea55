"""Queries of the methods and baselines themselves."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from histreplay.functions import codec
from histreplay.functions.digest import ordered
from histreplay.operators import affinity, baselines, batching, generations, history, mutable, project, protocol, replay, stripes, tier, verify
from histreplay.queries import sql
from histreplay.schema import DAY, EVENT_COLUMNS, HOUR, LayoutSpec, PointerSpec, TenantSpec
from histreplay.sources import tables
from histreplay.sources.scratch import folder

LAYOUT = LayoutSpec(stripe_len=8)
LENGTH = 16


def _hist(spark: SparkSession, sf_dir: str, key: str = "user") -> DataFrame:
    return history.canonical(tables.KEYED[key](spark, sf_dir))


#: What stored() has written in this process, by application and tables.
_stored: dict[tuple[str, str], tuple[generations.Registry, str]] = {}


def stored(spark: SparkSession, sf_dir: str) -> tuple[generations.Registry, DataFrame]:
    """The published generation 1 of the tables' history, encoded, and the slim examples logged against it, both in buckets of users.

    Written once for each application: a tier is bulk-loaded once and read by many jobs.
    """
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _stored:
        name, root = f"history_{uuid.uuid4().hex[:12]}", f"{folder(spark)}/tier-{uuid.uuid4().hex}"
        hist = _hist(spark, sf_dir)
        registry = generations.Registry(spark, name, LAYOUT, root)
        registry.write(stripes.build(hist, LAYOUT), 1, tier.plan(hist, EVENT_COLUMNS))
        registry.publish(1)
        slim = protocol.snapshot(history.requests_of(hist), hist)
        ready = slim.repartition(LAYOUT.buckets, "user_id").sortWithinPartitions("user_id", "t_us")
        ready.write.bucketBy(LAYOUT.buckets, "user_id").sortBy("user_id", "t_us").option("path", f"{root}/slim").saveAsTable(f"{name}_slim")
        _stored[key] = registry, f"{name}_slim"
    registry, slim_table = _stored[key]
    return registry, spark.table(slim_table)


def _case(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """History, requests, the stored slim examples, and the stripes of the pinned generation they were logged against."""
    hist = _hist(spark, sf_dir)
    registry, slim = stored(spark, sf_dir)
    return hist, history.requests_of(hist), slim, registry.read(1)


def _text(seq: DataFrame) -> DataFrame:
    return history.summary(seq)


def m01_canonical(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _hist(spark, sf_dir)


def m02_state_at(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    return _text(history.state_at(hist, history.requests_of(hist)))


def m03_no_future(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    rows = history.no_future(baselines.leaky(history.requests_of(hist), hist))
    return rows.groupBy("request_id").agg(F.count("*").alias("n"), F.max("us").alias("last_us"))


def m04_bifurcate(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    cutoff = hist.agg(F.max(F.floor(F.col("us") / DAY) * DAY)).first()[0]
    parts = [x.groupBy("user_id").agg(F.count("*").alias("n"), F.min("us").alias("first_us"), F.max("us").alias("last_us")).withColumn("part", F.lit(p)) for p, x in zip(("mutable", "immutable"), protocol.bifurcate(hist, cutoff))]
    return parts[0].unionByName(parts[1])


def m05_snapshot(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    asks = history.requests_of(hist)
    slim = protocol.snapshot(asks, hist, PointerSpec(digest="ordered"))
    p = F.get("pointers", F.lit(0))
    return slim.select("request_id", F.size("m_us").cast("long").alias("mutable"), F.coalesce(p["start_us"], F.lit(-1)).alias("start_us"), F.coalesce(p["end_us"], F.lit(-1)).alias("end_us"), F.coalesce(p["seq_len"], F.lit(0)).alias("seq_len"), p["digest"].alias("digest"))


def m05_no_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    found = protocol.pointers(history.requests_of(hist), hist, PointerSpec(digest=None))
    return found.select("request_id", *[F.coalesce(c, F.lit(-1)).alias(c) for c in ("start_us", "end_us")], "seq_len", "digest")


def m05_group_pointer(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    found = protocol.pointers(history.requests_of(hist), hist, PointerSpec(per_group=True))
    return found.filter("seq_len > 0").select("request_id", "feature_group", "start_us", "end_us", "seq_len", F.col("digest").cast("long").alias("digest"))


def m05_additive_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    found = protocol.pointers(history.requests_of(hist), hist)
    return found.select("request_id", "seq_len", F.col("digest").cast("long").alias("digest"))


def _stripe_rows(st: DataFrame) -> DataFrame:
    return st.select("user_id", "feature_group", "stripe_no", "first_us", "last_us", F.col("n_events").cast("long").alias("n_events"), "events_before", ordered(F.col("us"), F.col("event_id")).alias("digest"))


def m06_stripes_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _stripe_rows(stripes.build(_hist(spark, sf_dir), LayoutSpec(stripe_len=8, per_group=True)))


def m06_stripes_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _stripe_rows(stripes.build(_hist(spark, sf_dir), LayoutSpec(mode="time", span=DAY)))


def _replay(strategy: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        _, _, slim, st = _case(spark, sf_dir)
        return _text(replay.reconstruct(slim, st, None, strategy))

    return run


def _replay_length(strategy: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        _, _, slim, st = _case(spark, sf_dir)
        return _text(replay.reconstruct(slim, st, LENGTH, strategy))

    return run


def m07_interleave(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    asks = history.requests_of(hist)
    slim = protocol.snapshot(asks, hist, PointerSpec(per_group=True))
    return _text(replay.interleave(slim, stripes.build(hist, LayoutSpec(stripe_len=8, per_group=True)), LENGTH))


def m08_verify(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One event in 500 is tampered with in the tier: the checks must find the requests whose windows hold it."""
    hist, _, slim, _ = _case(spark, sf_dir)
    spoiled = hist.withColumn("event_id", F.when(F.col("event_id") % 500 == 0, F.col("event_id") + 1_000_000).otherwise(F.col("event_id")))
    asks = replay.unpack(slim).withColumn("need", F.col("seq_len"))
    read = replay.multi_range(asks, project.traits(stripes.build(spoiled, LAYOUT), ("us", "event_id")), "range")
    old = replay.cut(asks, read, ("us", "event_id")).withColumnsRenamed({"i_us": "us", "i_event_id": "event_id"})
    return verify.check(old.join(slim.select("request_id", "user_id"), "request_id"), asks)


def m10_retention_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    now = hist.agg(F.max("us")).first()[0]
    out = None
    for hours in (12, 24, 48):
        gap = protocol.retention_gaps(hist, now, hours * HOUR, now // DAY * DAY - DAY).agg(F.count("*").alias("lost")).withColumn("retention_hours", F.lit(hours))
        out = gap if out is None else out.unionByName(gap)
    return out


def m11_mutable_resolve(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    now = hist.agg(F.max("us")).first()[0]
    fragments = mutable.fragments(hist.unionByName(hist.filter("event_id % 7 = 0")), HOUR)
    return _text(mutable.resolve(fragments, now, 2 * DAY).withColumn("request_id", F.col("user_id"))).withColumnRenamed("request_id", "user_id")


def m11_mutable_compact(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    now = hist.agg(F.max("us")).first()[0]
    fragments = mutable.fragments(hist.unionByName(hist.filter("event_id % 7 = 0")), HOUR)
    return _text(mutable.resolve(mutable.compact(fragments), now, 2 * DAY).withColumn("request_id", F.col("user_id"))).withColumnRenamed("request_id", "user_id")


def _end(hist: DataFrame) -> int:
    return hist.agg(F.max(F.floor(F.col("us") / DAY) * DAY)).first()[0]


def m12_rebuild(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    return _stripe_rows(generations.rebuild(hist, _end(hist), lookback_days=14, layout=LAYOUT))


def m12_advance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The generation of the day before, moved on by one day; equals the rebuild."""
    hist = _hist(spark, sf_dir)
    end = _end(hist)
    previous = generations.rebuild(hist, end - DAY, lookback_days=14, layout=LAYOUT)
    day = hist.filter((F.col("us") >= end - DAY) & (F.col("us") < end))
    return _stripe_rows(generations.advance(previous, day, end, lookback_days=14, layout=LAYOUT))


def m12_content_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    return generations.content_digest(generations.rebuild(hist, _end(hist), lookback_days=14, layout=LAYOUT))


def m16_span(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, _, slim, st = _case(spark, sf_dir)
    asks = replay.unpack(slim).filter("seq_len > 0")
    found = project.spans(asks, st, LENGTH, LAYOUT.stripe_len).filter("need > 0")
    return found.select("request_id", "need", "lo", "hi")


def m17_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = stripes.build(_hist(spark, sf_dir), LayoutSpec(stripe_len=8, per_group=True))
    return stripes.explode(project.groups(st, ("dense", "sparse")), ("us", "event_id")).groupBy("feature_group").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


def m18_traits(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = project.traits(stripes.build(_hist(spark, sf_dir), LAYOUT), ("us", "item_id"))
    return st.select("user_id", "stripe_no", F.aggregate("item_id", F.lit(0).cast("long"), lambda a, x: a + x).alias("items"), F.array_max("us").alias("last_us"))


def m19_combined(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = stripes.build(_hist(spark, sf_dir), LayoutSpec(stripe_len=8, per_group=True))
    own = project.apply(st, TenantSpec("X", 16, groups=("sparse",), traits=("value",)), per_group=True)
    latest = own.groupBy("user_id", "feature_group").agg(F.max("stripe_no").alias("top"))
    return own.join(latest, ["user_id", "feature_group"]).filter("stripe_no >= top - 1").select("user_id", "stripe_no", F.size("value").cast("long").alias("n"), F.round(F.aggregate("value", F.lit(0.0), lambda a, x: a + x), 4).alias("value"))


def m20_multi_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, _, slim, st = _case(spark, sf_dir)
    asks = project.spans(replay.unpack(slim).filter("seq_len > 0"), st, LENGTH, LAYOUT.stripe_len).filter("need > 0")
    return replay.multi_range(asks, stripes.index(st), "equi", parallelism=4).groupBy("request_id").agg(F.count("*").alias("stripes"), F.sum("n_events").alias("elems"))


def m21_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = stripes.build(_hist(spark, sf_dir), LAYOUT).withColumn("code", codec.delta_encode(F.col("us"))).withColumn("back", codec.delta_decode(F.col("code")))
    return st.select("user_id", "stripe_no", F.get("code", F.lit(0)).alias("base"), F.aggregate(F.slice("code", F.lit(2), F.lit(1000)), F.lit(0).cast("long"), lambda a, x: a + x).alias("span"), (F.col("back") == F.col("us")).alias("same"))


def m21_bitmap(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = stripes.build(_hist(spark, sf_dir), LayoutSpec(stripe_len=70)).withColumn("flags", F.transform("event_type", lambda x: x == "purchase"))
    st = st.withColumn("words", codec.bitmap_encode(F.col("flags"))).withColumn("back", codec.bitmap_decode(F.col("words"), F.col("n_events")))
    ones = F.aggregate(F.transform("words", lambda w: F.bit_count(w)), F.lit(0), lambda a, x: a + x).cast("long")
    return st.select("user_id", "stripe_no", F.size("words").cast("long").alias("n_words"), ones.alias("ones"), (F.col("back") == F.col("flags")).alias("same"))


def m21_dict(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = stripes.build(_hist(spark, sf_dir), LAYOUT)
    words, codes = codec.dict_encode(F.col("event_type"))
    st = st.withColumns({"words": words, "codes": codes}).withColumn("back", codec.dict_decode(F.col("words"), F.col("codes")))
    return st.select("user_id", "stripe_no", F.array_join("words", ",").alias("words"), F.array_join(F.transform("codes", lambda c: c.cast("string")), ",").alias("codes"), (F.col("back") == F.col("event_type")).alias("same"))


def m27_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    return batching.base(history.requests_of(hist), 256, "request_id").groupBy("batch_id").agg(F.count("*").alias("n"), F.min("request_id").alias("first_id"), F.max("request_id").alias("last_id"))


def m27_base_by_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    sizes = protocol.pointers(history.requests_of(hist), hist, PointerSpec(digest=None)).select("request_id", (8 * F.col("seq_len")).alias("bytes"))
    return batching.base_by_bytes(sizes, 65536, "request_id", "bytes").groupBy("batch_id").agg(F.count("*").alias("n"), F.sum("bytes").alias("bytes"))


def m28_rebatch(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    full = batching.rebatch(batching.base(history.requests_of(hist), 256, "request_id"), 512, seed=3, id_col="request_id")
    return full.groupBy("full_id").agg(F.count("*").alias("n"), F.sum("request_id").alias("ids"), F.count_distinct("batch_id").alias("sources"))


def m32_cluster(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    return affinity.lookups(history.requests_of(hist), HOUR).groupBy("slot").agg(F.count("*").alias("lookups"), F.sum("requests").alias("requests"))


def b1_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    return _text(baselines.wide_row(history.requests_of(hist), hist, 64))


def b1b_truncate(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    return _text(baselines.truncate(baselines.wide_row(history.requests_of(hist), hist, 64), LENGTH))


def b2_etl(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    rows = baselines.etl_join(history.requests_of(hist), hist)
    return rows.groupBy("request_id").agg(F.count("*").alias("n"), F.count_if(F.col("us") > F.col("t_us")).alias("leaked"))


def b2a_leaky(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    rows = baselines.leaky(history.requests_of(hist), hist)
    return rows.groupBy("request_id").agg(F.count("*").alias("n"), F.count_if(F.col("us") > F.col("t_us")).alias("leaked"))


def b3_lsm(spark: SparkSession, sf_dir: str) -> DataFrame:
    runs = baselines.lsm(_hist(spark, sf_dir), 4)
    return runs.groupBy("run_lo").agg(F.count("*").alias("n"), F.max("merges").cast("long").alias("merges"))


def b4_append_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.append_store(_hist(spark, sf_dir)).groupBy("user_id").agg(F.count_distinct("run_lo").alias("runs"))


def b6_monolith(spark: SparkSession, sf_dir: str) -> DataFrame:
    blob = baselines.monolith(_hist(spark, sf_dir))
    return blob.select("user_id", F.size("events").cast("long").alias("n"), F.round(F.aggregate("events", F.lit(0.0), lambda a, e: a + e["value"]), 4).alias("value"))


_B = sql.base()
_D = sql.DIGEST
_IMMUTABLE = "(SELECT * FROM W WHERE us < c_us)"


def _stripe_sql(source: str, no: str, group: str) -> str:
    return f"""SELECT user_id, feature_group, stripe_no, min(us) AS first_us, max(us) AS last_us, count(*) AS n_events, CAST(min(rank) AS BIGINT) AS events_before, {_D} AS digest
FROM (SELECT *, CAST({no} AS BIGINT) AS stripe_no FROM (SELECT user_id, {group} AS feature_group, us, event_id, row_number() OVER (PARTITION BY user_id, {group} ORDER BY us, event_id) - 1 AS rank FROM {source}))
GROUP BY user_id, feature_group, stripe_no"""


_GEN = f"(SELECT * FROM H WHERE us < (SELECT max(us // {DAY} * {DAY}) FROM H) AND us >= (SELECT max(us // {DAY} * {DAY}) FROM H) - 14 * {DAY})"
_MUT = f"(SELECT * FROM H WHERE us >= (SELECT max(us) FROM H) - 2 * {DAY})"
_ST = f"ST AS (SELECT *, CAST((row_number() OVER (PARTITION BY user_id ORDER BY us, event_id) - 1) // 8 AS BIGINT) AS stripe_no FROM H)"
_SPAN = f"SP AS (SELECT request_id, count(*) AS need, min(stripe_no) AS lo, max(stripe_no) AS hi FROM {sql.tail(LENGTH)} w JOIN ST USING (user_id, us, event_id) GROUP BY request_id)"

QUERIES = {
    "m01_canonical": (m01_canonical, f"WITH {sql.HIST} SELECT * FROM H"),
    "m02_state_at": (m02_state_at, f"{_B} {sql.SUMMARY} GROUP BY request_id"),
    "m03_no_future": (m03_no_future, f"WITH {sql.HIST} SELECT r.event_id AS request_id, count(*) AS n, max(h.us) AS last_us FROM H r JOIN H h ON h.user_id = r.user_id AND h.us <= r.us WHERE r.event_type = 'view' GROUP BY r.event_id"),
    "m04_bifurcate": (m04_bifurcate, f"WITH {sql.HIST} SELECT user_id, count(*) AS n, min(us) AS first_us, max(us) AS last_us, CASE WHEN us >= (SELECT max(us // {DAY} * {DAY}) FROM H) THEN 'mutable' ELSE 'immutable' END AS part FROM H GROUP BY user_id, part"),
    "m05_snapshot": (m05_snapshot, f"{_B} SELECT R.request_id, coalesce(m.n, 0) AS mutable, coalesce(start_us, -1) AS start_us, coalesce(end_us, -1) AS end_us, coalesce(seq_len, 0) AS seq_len, digest FROM R LEFT JOIN (SELECT request_id, count(*) AS n FROM W WHERE us >= c_us GROUP BY 1) m USING (request_id) LEFT JOIN (SELECT request_id, min(us) AS start_us, max(us) AS end_us, count(*) AS seq_len, {_D} AS digest FROM {_IMMUTABLE} GROUP BY 1) i USING (request_id)"),
    "m05_no_digest": (m05_no_digest, f"{_B} SELECT R.request_id, coalesce(start_us, -1) AS start_us, coalesce(end_us, -1) AS end_us, coalesce(seq_len, 0) AS seq_len, CAST(NULL AS VARCHAR) AS digest FROM R LEFT JOIN (SELECT request_id, min(us) AS start_us, max(us) AS end_us, count(*) AS seq_len FROM {_IMMUTABLE} GROUP BY 1) i USING (request_id)"),
    "m05_group_pointer": (m05_group_pointer, f"{_B} SELECT request_id, feature_group, min(us) AS start_us, max(us) AS end_us, count(*) AS seq_len, CAST(sum({sql.HASH32}) % 4294967296 AS BIGINT) AS digest FROM {_IMMUTABLE} GROUP BY request_id, feature_group"),
    "m05_additive_digest": (m05_additive_digest, f"{_B} SELECT R.request_id, coalesce(n, 0) AS seq_len, CAST(coalesce(d, 0) AS BIGINT) AS digest FROM R LEFT JOIN (SELECT request_id, count(*) AS n, sum({sql.HASH32}) % 4294967296 AS d FROM {_IMMUTABLE} GROUP BY 1) USING (request_id)"),
    "m06_stripes_count": (m06_stripes_count, f"WITH {sql.HIST} {_stripe_sql('H', 'rank // 8', 'feature_group')}"),
    "m06_stripes_time": (m06_stripes_time, f"WITH {sql.HIST} " + _stripe_sql("H", f"us // {DAY}", "'all'")),
    **{f"m07_{s}": (_replay(s), f"{_B} {sql.SUMMARY} GROUP BY request_id") for s in replay.STRATEGIES},
    **{f"m07_{s}_16": (_replay_length(s), f"{_B} {sql.SUMMARY} WHERE back <= {LENGTH} GROUP BY request_id") for s in replay.STRATEGIES},
    "m07_interleave": (m07_interleave, f"{_B} {sql.SUMMARY} WHERE back <= {LENGTH} GROUP BY request_id"),
    "m08_verify": (m08_verify, f"{_B} SELECT request_id, CASE WHEN bool_or(event_id % 500 = 0) THEN 'digest_mismatch' ELSE 'ok' END AS status FROM {_IMMUTABLE} GROUP BY request_id"),
    "m10_retention_gap": (m10_retention_gap, f"WITH {sql.HIST} SELECT CAST(hours AS INTEGER) AS retention_hours, (SELECT count(*) FROM H WHERE us >= (SELECT max(us) FROM H) // {DAY} * {DAY} - {DAY} AND us < (SELECT max(us) FROM H) - hours * {HOUR}) AS lost FROM (VALUES (12), (24), (48)) v(hours)"),
    "m11_mutable_resolve": (m11_mutable_resolve, f"WITH {sql.HIST} SELECT user_id, count(*) AS n, min(us) AS first_us, max(us) AS last_us, {_D} AS digest FROM {_MUT} GROUP BY user_id"),
    "m11_mutable_compact": (m11_mutable_compact, f"WITH {sql.HIST} SELECT user_id, count(*) AS n, min(us) AS first_us, max(us) AS last_us, {_D} AS digest FROM {_MUT} GROUP BY user_id"),
    "m12_rebuild": (m12_rebuild, f"WITH {sql.HIST} " + _stripe_sql(_GEN, "rank // 8", "'all'")),
    "m12_advance": (m12_advance, f"WITH {sql.HIST} " + _stripe_sql(_GEN, "rank // 8", "'all'")),
    "m12_content_digest": (m12_content_digest, f"WITH {sql.HIST} SELECT count(*) AS events, CAST(sum({sql.HASH32}) AS BIGINT) AS digest FROM {_GEN}"),
    "m16_span": (m16_span, f"{_B.rstrip()}, {_ST}, {_SPAN} SELECT * FROM SP"),
    "m17_groups": (m17_groups, f"WITH {sql.HIST} SELECT feature_group, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM H WHERE feature_group IN ('dense', 'sparse') GROUP BY feature_group"),
    "m18_traits": (m18_traits, f"WITH {sql.HIST}, {_ST} SELECT user_id, stripe_no, CAST(sum(item_id) AS BIGINT) AS items, max(us) AS last_us FROM ST GROUP BY user_id, stripe_no"),
    "m19_combined": (m19_combined, f"WITH {sql.HIST}, N AS (SELECT *, CAST((row_number() OVER (PARTITION BY user_id ORDER BY us, event_id) - 1) // 8 AS BIGINT) AS stripe_no FROM H WHERE feature_group = 'sparse') SELECT user_id, stripe_no, count(*) AS n, round(sum(value), 4) AS value FROM N WHERE stripe_no >= (SELECT max(x.stripe_no) - 1 FROM N x WHERE x.user_id = N.user_id) GROUP BY user_id, stripe_no"),
    "m20_multi_range": (m20_multi_range, f"{_B.rstrip()}, {_ST}, {_SPAN} SELECT request_id, count(DISTINCT s.stripe_no) AS stripes, count(*) AS elems FROM SP JOIN R USING (request_id) JOIN ST s ON s.user_id = R.user_id AND s.stripe_no BETWEEN lo AND hi GROUP BY request_id"),
    "m21_delta": (m21_delta, f"WITH {sql.HIST}, {_ST} SELECT user_id, stripe_no, min(us) AS base, max(us) - min(us) AS span, true AS same FROM ST GROUP BY user_id, stripe_no"),
    "m21_bitmap": (m21_bitmap, f"WITH {sql.HIST}, N AS (SELECT *, CAST((row_number() OVER (PARTITION BY user_id ORDER BY us, event_id) - 1) // 70 AS BIGINT) AS stripe_no FROM H) SELECT user_id, stripe_no, CAST(ceil(count(*) / 64.0) AS BIGINT) AS n_words, count(*) FILTER (event_type = 'purchase') AS ones, true AS same FROM N GROUP BY user_id, stripe_no"),
    "m21_dict": (m21_dict, f"WITH {sql.HIST}, {_ST}, K AS (SELECT user_id, stripe_no, list_sort(list_distinct(list(event_type))) AS words, list(event_type ORDER BY us, event_id) AS kinds FROM ST GROUP BY user_id, stripe_no) SELECT user_id, stripe_no, array_to_string(words, ',') AS words, array_to_string(list_transform(kinds, lambda k: list_position(words, k) - 1), ',') AS codes, true AS same FROM K"),
    "m27_base": (m27_base, f"WITH {sql.HIST}, {sql.requests()}, B AS (SELECT request_id, CAST((row_number() OVER (ORDER BY request_id) - 1) // 256 AS BIGINT) AS batch_id FROM R) SELECT batch_id, count(*) AS n, min(request_id) AS first_id, max(request_id) AS last_id FROM B GROUP BY batch_id"),
    "m27_base_by_bytes": (m27_base_by_bytes, f"{_B.rstrip()}, S AS (SELECT R.request_id, 8 * count(W.us) FILTER (W.us < W.c_us) AS bytes FROM R LEFT JOIN W USING (request_id) GROUP BY 1), B AS (SELECT *, CAST(coalesce(sum(bytes) OVER (ORDER BY request_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // 65536 AS BIGINT) AS batch_id FROM S) SELECT batch_id, count(*) AS n, CAST(sum(bytes) AS BIGINT) AS bytes FROM B GROUP BY batch_id"),
    "m28_rebatch": (m28_rebatch, f"WITH {sql.HIST}, {sql.requests()}, B AS (SELECT request_id, (row_number() OVER (ORDER BY request_id) - 1) // 256 AS batch_id, (row_number() OVER (ORDER BY md5(request_id || ':3'), request_id) - 1) // 512 AS full_id FROM R) SELECT CAST(full_id AS BIGINT) AS full_id, count(*) AS n, CAST(sum(request_id) AS BIGINT) AS ids, count(DISTINCT batch_id) AS sources FROM B GROUP BY full_id"),
    "m32_cluster": (m32_cluster, f"WITH {sql.HIST}, {sql.requests()} SELECT t_us // {HOUR} AS slot, count(DISTINCT user_id) AS lookups, count(*) AS requests FROM R GROUP BY slot"),
    "b1_wide": (b1_wide, f"{_B} {sql.SUMMARY} WHERE back <= 64 GROUP BY request_id"),
    "b1b_truncate": (b1b_truncate, f"{_B} {sql.SUMMARY} WHERE back <= {LENGTH} GROUP BY request_id"),
    "b2_etl": (b2_etl, f"WITH {sql.HIST}, {sql.requests()} SELECT request_id, count(*) AS n, count(*) FILTER (h.us > t_us) AS leaked FROM R JOIN H h ON h.user_id = R.user_id AND h.us < (t_us // {DAY} + 1) * {DAY} GROUP BY request_id"),
    "b2a_leaky": (b2a_leaky, f"WITH {sql.HIST}, {sql.requests()} SELECT request_id, count(*) AS n, count(*) FILTER (h.us > t_us) AS leaked FROM R JOIN H h ON h.user_id = R.user_id GROUP BY request_id"),
    "b3_lsm": (b3_lsm, f"WITH {sql.HIST}, D AS (SELECT us // {DAY} - (SELECT min(us) // {DAY} FROM H) AS d FROM H), P AS (SELECT CASE WHEN d < 16 THEN 0 WHEN d < 28 THEN 16 + (d - 16) // 4 * 4 ELSE d END AS run_lo, CASE WHEN d < 16 THEN 2 WHEN d < 28 THEN 1 ELSE 0 END AS merges FROM D) SELECT run_lo, count(*) AS n, max(merges) AS merges FROM P GROUP BY run_lo"),
    "b4_append_store": (b4_append_store, f"WITH {sql.HIST} SELECT user_id, count(DISTINCT us // {DAY}) AS runs FROM H GROUP BY user_id"),
    "b6_monolith": (b6_monolith, f"WITH {sql.HIST} SELECT user_id, count(*) AS n, round(sum(value), 4) AS value FROM H GROUP BY user_id"),
}
