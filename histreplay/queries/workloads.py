"""The experiment workloads on the given tables."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from histreplay.functions import codec, quality
from histreplay.functions.digest import event_hash, ordered
from histreplay.operators import affinity, baselines, batching, generations, history, layers, protocol, replay, stripes, verify
from histreplay.plans import autoscale, cost, prefetch
from histreplay.queries import sql
from histreplay.queries.methods import LAYOUT, _case, _end, _hist, stored
from histreplay.schema import DAY, HOUR, TENANTS, LayoutSpec, PointerSpec, TenantSpec
from histreplay.sources import tables
from histreplay.sources.scratch import folder

TOP = max(t.seq_len for t in TENANTS)
NE_LENGTHS = (4, 16, 64)
LADDER = (64, 256, 1024, 4096)


def _counts(spark: SparkSession, sf_dir: str, key: str = "user") -> DataFrame:
    hist = _hist(spark, sf_dir, key)
    return cost.request_counts(history.requests_of(hist), hist)


def _asks(slim: DataFrame) -> DataFrame:
    return replay.unpack(slim).filter("seq_len > 0")


def w01_primary_write(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cost.primary_write(_counts(spark, sf_dir), TOP)


def w02_primary_read(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cost.primary_read(_counts(spark, sf_dir))


def _light_asks(hist: DataFrame) -> DataFrame:
    """Pointers with the length of the logged part, without the logged part itself."""
    asks = history.requests_of(hist)
    mutable = cost.request_counts(asks, hist).select("request_id", "mutable")
    return protocol.pointers(asks, hist, PointerSpec(digest=None)).filter("seq_len > 0").join(mutable, "request_id")


def _lookups(spark: SparkSession, sf_dir: str, key: str, window: int | None, tenants: tuple[TenantSpec, ...] = TENANTS) -> DataFrame:
    hist = _hist(spark, sf_dir, key)
    return cost.lookup(_light_asks(hist), stripes.build(hist, LAYOUT, ("us", "event_id")), tenants, LAYOUT.stripe_len, window)


def w03_lookup_streaming(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = _counts(spark, sf_dir).agg(cost.wide_elems(None, TOP).alias("base"))
    return _lookups(spark, sf_dir, "user", None).crossJoin(F.broadcast(base)).select("tenant", "lookups", "lookup_elems", (F.col("lookup_elems") / F.col("base")).alias("pct"))


def w03_lookup_hourly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The batch form of w03: one lookup for each nation and hour."""
    base = _counts(spark, sf_dir, "nation").agg(cost.wide_elems(None, TOP).alias("base"))
    return _lookups(spark, sf_dir, "nation", HOUR).crossJoin(F.broadcast(base)).select("tenant", "lookups", "lookup_elems", (F.col("lookup_elems") / F.col("base")).alias("pct"))


def w04_lookup_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for key in ("user", "nation", "region"):
        asks = history.requests_of(_hist(spark, sf_dir, key))
        for name, window in (("hour", HOUR), ("day", DAY)):
            own = affinity.lookups(asks, window).agg(F.count("*").alias("lookups"), F.sum("requests").alias("requests")).select(F.lit(key).alias("key"), F.lit(name).alias("slot"), "lookups", "requests", (F.col("lookups") / F.col("requests")).alias("pct"))
            out = own if out is None else out.unionByName(own)
    return out


def w05_latency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measured here: (tenant, measure, value), from stored examples, stored stripes and stored wide rows, batch by batch.

    latency_change: seconds a batch by replay over those from wide rows, minus 1; rate_*: examples a second and worker.
    """
    hist = _hist(spark, sf_dir)
    registry, slim = stored(spark, sf_dir)
    path = f"{folder(spark)}/wide-{uuid.uuid4().hex}"
    baselines.wide_row(history.requests_of(hist), hist, TOP).write.parquet(path)
    wide, rows = spark.read.parquet(path), []
    for t in TENANTS:
        stripes_of = registry.read(1, tuple(dict.fromkeys(("us", "event_id", *t.traits))))
        for batch in range(2):
            mine = F.pmod("request_id", F.lit(2)) == batch
            for mode, df in (("replay", replay.reconstruct(slim.filter(mine), stripes_of, t.seq_len, "affinity")), ("wide", baselines.truncate(wide.filter(mine), t.seq_len))):
                began = time.perf_counter()
                n = history.summary(df).count()
                rows.append((t.name, mode, time.perf_counter() - began, n, spark.sparkContext.defaultParallelism))
    runs = spark.createDataFrame(rows, "tenant string, mode string, seconds double, rows long, workers int")
    latency = cost.batch_latency(runs).select("tenant", F.lit("latency_change").alias("measure"), F.col("change").alias("value"))
    rates = cost.throughput(runs).select(F.lit("all").alias("tenant"), F.concat(F.lit("rate_"), "mode").alias("measure"), F.col("rate").alias("value"))
    return latency.unionByName(rates)


def _size(spark: SparkSession, df: DataFrame, tag: str) -> int:
    """Bytes of the files that a table makes; only their lengths are read back."""
    path = f"{folder(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).agg(F.sum("length")).first()[0] or 0


def w35_table1_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(tenant, measure, bytes, base, change) in bytes of written files, where examples also carry features of the user.

    write: slim examples over wide rows. read: the tenant's tail of the logged arrays over whole wide rows. lookup_user
    and lookup_nation_hour: bytes of the encoded stripes that lookups read, one a request, or one a nation and hour,
    over the wide read of their own examples' elements. density: encoded over plain stripes.
    """
    hist = _hist(spark, sf_dir)
    registry, slim = stored(spark, sf_dir)
    other = tables.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), *[F.col(c) for c in ("c_name", "c_nationkey", "c_acctbal", "c_mktsegment")])
    full = lambda df: df.join(other, "user_id", "left").repartitionByRange(LAYOUT.buckets, "request_id").sortWithinPartitions("request_id")
    wide = full(baselines.wide_row(history.requests_of(hist), hist, TOP))
    wide_bytes, slim_bytes = _size(spark, wide, "wide"), _size(spark, full(slim), "slim")
    st = registry.read(1)
    plain = _size(spark, st.repartition(LAYOUT.buckets, "user_id").sortWithinPartitions("user_id", "first_us"), "plain")
    stored_stripes = spark.table(registry.table(1))
    encoded = _size(spark, stored_stripes.repartition(LAYOUT.buckets, "user_id").sortWithinPartitions("user_id", "first_us"), "encoded")
    elems = st.agg(F.sum("n_events")).first()[0]
    rows = [("all", "write", slim_bytes, wide_bytes), ("all", "density", encoded, plain)]
    logged = [c for c in slim.columns if c.startswith("m_")]
    per_elem = {"user": wide_bytes / max(1, _counts(spark, sf_dir).agg(cost.wide_elems(None, TOP)).first()[0])}
    bases = {k: _counts(spark, sf_dir, k).agg(cost.wide_elems(None, TOP)).first()[0] for k in ("user", "nation")}
    for t in TENANTS:
        cut = slim.withColumns({c: replay._tail(F.col(c), F.lit(t.seq_len)) for c in logged})
        rows.append((t.name, "read", _size(spark, full(cut), "read"), wide_bytes))
    for key, window in (("user", None), ("nation", HOUR)):
        for r in _lookups(spark, sf_dir, key, window).collect():
            rows.append((r["tenant"], "lookup_user" if key == "user" else "lookup_nation_hour", int(r["lookup_elems"] * encoded / elems), int(bases[key] * per_elem["user"])))
    found = spark.createDataFrame(rows, "tenant string, measure string, bytes long, base long")
    return found.withColumn("change", F.col("bytes") / F.col("base") - F.when(F.col("measure").isin("write", "read"), 1).otherwise(0))


def w06_fleet(spark: SparkSession, sf_dir: str) -> DataFrame:
    read = cost.primary_read(_counts(spark, sf_dir)).drop("reduction")
    both = read.join(_lookups(spark, sf_dir, "user", HOUR).select("tenant", "lookup_elems"), "tenant").select("tenant", "base", (F.col("ours") + F.col("lookup_elems") / cost.READ_RATIO).alias("ours"))
    return cost.fleet(both, {t.name: t.jobs for t in TENANTS})


def w07_effective(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    runs = cost.days_touched(hist, history.requests_of(hist), 30).agg(F.avg("runs").alias("day_runs"))
    return w03_lookup_streaming(spark, sf_dir).select("tenant", cost.effective_footprint(F.col("pct")).alias("effective")).crossJoin(F.broadcast(runs)).withColumn("single_level_runs", F.lit(1))


def w08_base_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    sizes = _counts(spark, sf_dir, "nation").select("request_id", F.least(F.col("seq_len") + F.col("mutable"), F.lit(1024)).alias("elems"))
    return batching.sweep(sizes, (64, 256, 1024, 4096), "request_id", "elems")


def _batch_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _counts(spark, sf_dir, "nation").select("request_id", F.col("mutable").alias("read_cost"), F.least("seq_len", F.greatest(F.lit(0), 64 - F.col("mutable"))).alias("lookup_cost"))
    timed = batching.base(rows, 64, "request_id").groupBy("batch_id").agg(F.sum("read_cost").alias("read_cost"), F.sum("lookup_cost").alias("lookup_cost"))
    return timed.withColumn("worker", F.col("batch_id") % 4)


def w09_prefetch(spark: SparkSession, sf_dir: str) -> DataFrame:
    times = _batch_times(spark, sf_dir)
    serial, piped = prefetch.makespan(times, False), prefetch.makespan(times, True)
    both = serial.select(F.col("makespan").alias("serial")).crossJoin(piped.select(F.col("makespan").alias("pipelined")))
    return both.withColumn("gain", F.col("serial") / F.col("pipelined") - 1)


def w10_affinity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lookups, and shards that a batch of 64 touches: examples in time order, clustered as the tier is, and clustered otherwise.

    Clustered batches are cut from the examples in order of 8 shards of users; the tier has 8 shards too, or 6.
    """
    asks = history.requests_of(_hist(spark, sf_dir, "nation"))
    n = asks.agg(F.count("*").alias("lookups"))
    slots = affinity.lookups(asks, HOUR).agg(F.count("*").alias("lookups"))
    plain = affinity.fanout(batching.base(asks, 64, "request_id"), 8)
    own = batching.clustered(asks, 64, F.pmod("user_id", F.lit(8)), "request_id")
    modes = {"plain": (n, plain), "affinity": (slots, affinity.fanout(own, 8)), "asymmetric": (slots, affinity.fanout(own, 6))}
    out = None
    for mode, (lookups, shards) in modes.items():
        one = lookups.crossJoin(shards.agg(F.avg("shards").alias("fanout"))).withColumn("mode", F.lit(mode))
        out = one if out is None else out.unionByName(one)
    return out


def _ladder(counts: DataFrame, lengths: tuple[int, ...]) -> DataFrame:
    logged = F.least(F.col("mutable"), F.col("length"))
    rows = counts.select("*", F.explode(F.array(*[F.lit(x) for x in lengths])).alias("length"))
    return rows.groupBy("length").agg(F.sum(F.least(F.col("seq_len") + F.col("mutable"), F.col("length"))).alias("wide_elems"), F.sum(logged).alias("logged_elems"), F.sum(F.least("seq_len", F.greatest(F.lit(0), F.col("length") - F.col("mutable")))).alias("replay_elems"))


def w11_ladder(spark: SparkSession, sf_dir: str) -> DataFrame:
    user = _ladder(_counts(spark, sf_dir), (4, 8, 16, 32, 64)).withColumn("key", F.lit("user"))
    nation = _ladder(_counts(spark, sf_dir, "nation"), LADDER).withColumn("key", F.lit("nation"))
    region = _ladder(_counts(spark, sf_dir, "region"), (*LADDER, 16384)).withColumn("key", F.lit("region"))
    return user.unionByName(nation).unionByName(region)


def _scored(seq: DataFrame, labels: DataFrame, length: int) -> DataFrame:
    kinds = F.col("event_type")
    bought = F.size(F.filter(kinds, lambda x: x == "purchase"))
    base = labels.agg(F.avg(F.col("label").cast("double")).alias("base"))
    rows = seq.select("request_id", bought.alias("bought"), F.size(kinds).alias("n")).join(labels.select("request_id", "label"), "request_id").crossJoin(F.broadcast(base))
    return rows.select(F.lit(length).alias("length"), "label", quality.rate(F.col("bought"), F.col("n"), F.col("base")).alias("p"))


def _ne(spark: SparkSession, sf_dir: str, lengths: tuple[int, ...], modes: tuple[str, ...]) -> DataFrame:
    hist, asks, slim, st = _case(spark, sf_dir)
    labels = history.label(asks, hist)
    out = None
    for n in lengths:
        for mode in modes:
            seq = baselines.truncate(baselines.wide_row(asks, hist, TOP), n) if mode == "wide" else replay.reconstruct(slim, st, n, "equi", LAYOUT.stripe_len, ("us", "event_id", "event_type"))
            own = quality.ne(_scored(seq, labels, n), ["length"]).withColumn("mode", F.lit(mode))
            out = own if out is None else out.unionByName(own)
    return out


def w12_ne_parity(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = _ne(spark, sf_dir, NE_LENGTHS, ("wide", "replay"))
    return found.groupBy("length").agg(F.round(F.max(F.when(F.col("mode") == "wide", F.col("ne"))), 9).alias("ne_wide"), F.round(F.max(F.when(F.col("mode") == "replay", F.col("ne"))), 9).alias("ne_replay"))


def w13_ne_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = _ne(spark, sf_dir, (4, 8, 16, 32, 64), ("replay",))
    first = F.first("ne").over(Window.partitionBy("mode").orderBy("length"))
    return found.select("length", F.round("ne", 9).alias("ne"), F.round((first - F.col("ne")) / first, 9).alias("gain"))


def _is(kind: str):
    return lambda x: x == kind


def w13_ne_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A logistic regression on counts of event types among the last events, by length; trained on even users, judged on odd."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.functions import vector_to_array

    hist, asks, slim, st = _case(spark, sf_dir)
    labels = history.label(asks, hist).select("request_id", "label")
    out = None
    for n in NE_LENGTHS:
        seq = replay.reconstruct(slim, st, n, "equi", LAYOUT.stripe_len, ("us", "event_id", "event_type"))
        kinds = ("view", "click", "purchase", "signup", "error")
        rows = seq.select("request_id", "user_id", *[F.size(F.filter("event_type", _is(k))).cast("double").alias(k) for k in kinds]).join(labels, "request_id")
        ready = VectorAssembler(inputCols=list(kinds), outputCol="x").transform(rows)
        model = LogisticRegression(featuresCol="x", labelCol="label", regParam=0.01).fit(ready.filter("user_id % 2 = 0"))
        scored = model.transform(ready.filter("user_id % 2 = 1")).select(F.lit(n).alias("length"), "label", quality.clipped(vector_to_array("probability")[1]).alias("p"))
        own = quality.ne(scored, ["length"])
        out = own if out is None else out.unionByName(own)
    return out


def wall_curve(spark: SparkSession, sf_dir: str, lengths: tuple[int, ...]) -> DataFrame:
    """(length, mode, ratio) by the unit cost model: whole rows carry `length` events.

    Replay carries what the ladder counts for that length on the region key, the share of logged elements, and of
    looked up ones by the reported read ratio.
    """
    costs = cost.UnitCosts()
    share = (F.col("logged_elems") + F.col("replay_elems") / cost.READ_RATIO) / F.col("wide_elems")
    rows = _ladder(_counts(spark, sf_dir, "region"), lengths).select("length", share.alias("share"))
    modes = F.explode(F.array(F.struct(F.lit("wide").alias("mode"), F.lit(1.0).alias("share")), F.struct(F.lit("replay").alias("mode"), F.col("share").alias("share")))).alias("m")
    return rows.select("length", modes).select("length", "m.mode", costs.ratio(F.col("m.share") * F.col("length"), F.col("length")).alias("ratio"))


def w14_wall(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = wall_curve(spark, sf_dir, tuple(1 << k for k in range(8, 17)))
    return found.select("length", "mode", F.round("ratio", 9).alias("ratio"), (F.col("ratio") > cost.UnitCosts().limit).alias("over"))


def w15_ab(spark: SparkSession, sf_dir: str) -> DataFrame:
    users = _hist(spark, sf_dir).groupBy("user_id").agg(F.count("*").alias("events"), F.sum("value").alias("value"), F.count_if(F.col("event_type") == "purchase").alias("purchases"), F.count_if(F.col("event_type") == "signup").alias("signups")).withColumn("arm", (F.col("user_id") % 2).cast("int"))
    return quality.ab(users, "arm", {"topline": F.col("events"), "consumption": F.col("value"), "explicit_purchase": F.col("purchases"), "explicit_signup": F.col("signups")}).select("metric", F.round("gain", 9).alias("gain"))


def w16_amplify_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    grid = history.k_grid(hist, (1, 2, 4, 8)).withColumn("request_id", F.lit(0))
    return cost.redundancy(history.window_events(grid, hist, 7), ["k"])


def w17_tenant_penalty(spark: SparkSession, sf_dir: str) -> DataFrame:
    user = cost.over_read(_counts(spark, sf_dir), (TenantSpec("short", 4), TenantSpec("long", 64))).withColumn("key", F.lit("user"))
    region = cost.over_read(_counts(spark, sf_dir, "region"), (TenantSpec("short", 100), TenantSpec("long", 10_000))).withColumn("key", F.lit("region"))
    return user.unionByName(region)


def w18_fidelity(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, _, slim, st = _case(spark, sf_dir)
    return history.summary(replay.reconstruct(slim, st, None, "affinity"))


def w19_leakage(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist, asks, slim, st = _case(spark, sf_dir)
    ours = replay.reconstruct(slim, st, None, "affinity").select("request_id", "t_us", F.explode("us").alias("us"))
    out = None
    for name, rows in (("etl_join", baselines.etl_join(asks, hist)), ("latest_state", baselines.leaky(asks, hist)), ("replay", ours)):
        own = verify.leakage(rows).withColumn("method", F.lit(name))
        out = own if out is None else out.unionByName(own)
    return out


def w20_layered(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    rows = layers.of_requests(history.window_events(history.requests_of(hist), hist), {"dense": 7, "sparse": 30})
    return rows.groupBy("request_id").agg(F.count_if(F.col("feature_group") == "dense").alias("n_dense"), F.count_if(F.col("feature_group") == "sparse").alias("n_sparse"))


def _deleted(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    items = tables.table(spark, sf_dir, "labels").filter("toxic = 1").select(F.col("doc_id").cast("int").alias("item_id"))
    users = tables.table(spark, sf_dir, "customer").filter("c_acctbal < 0").select(F.col("c_custkey").alias("user_id"))
    return items, users


def w21_delete(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    items, users = _deleted(spark, sf_dir)
    kept = stripes.explode(generations.rebuild(hist, _end(hist) + DAY, 60, LAYOUT, items, users), ("us", "event_id"))
    total = hist.agg(F.count("*").alias("total"))
    sums = kept.agg(F.count("*").alias("kept"), F.sum(event_hash(F.col("us"), F.col("event_id"))).alias("digest"))
    return sums.crossJoin(total).select("kept", (F.col("total") - F.col("kept")).alias("scrubbed"), "digest")


def w21_scrub_logged(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, _, slim, _ = _case(spark, sf_dir)
    items, _ = _deleted(spark, sf_dir)
    return replay.scrub_logged(slim, items).select("request_id", F.size("m_us").cast("long").alias("mutable"))


def w22_sideinfo(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    lang = tables.table(spark, sf_dir, "documents").select(F.col("doc_id").cast("int").alias("item_id"), "lang")
    brand = tables.table(spark, sf_dir, "part").select(F.col("p_partkey").cast("int").alias("item_id"), F.col("p_brand").alias("brand"))
    gen = generations.rebuild(hist, _end(hist), 30, LAYOUT, add=(generations.SideInfo(lang, "lang"), generations.SideInfo(brand, "brand")), drop=("value",))
    text = F.transform(F.arrays_zip("event_id", "lang", "brand"), lambda e: F.concat_ws(":", e["event_id"].cast("string"), F.coalesce(e["lang"], F.lit("-")), F.coalesce(e["brand"], F.lit("-"))))
    return gen.select("user_id", "stripe_no", F.md5(F.concat_ws(",", text)).alias("digest"))


def w23_lsm(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    asks = history.requests_of(hist).withColumns({"hi": protocol.cutoff_of(F.col("t_us"))}).withColumn("lo", F.col("hi") - 29 * DAY)
    layouts = {"append_days": baselines.append_store(hist).withColumn("merges", F.lit(0)), "multi_level": baselines.lsm(hist, 4), "single_level": hist.withColumns({"run_lo": F.lit(0), "merges": F.lit(0)})}
    out = None
    for name, store in layouts.items():
        runs = asks.join(store.select("user_id", "us", "run_lo"), "user_id").filter("us < hi and us >= lo").groupBy("request_id").agg(F.count_distinct("run_lo").alias("runs"))
        amp = store.agg((1 + F.avg("merges")).alias("write_amp"))
        own = runs.agg(F.avg("runs").alias("mean_runs"), F.max("runs").alias("max_runs")).crossJoin(amp).withColumn("layout", F.lit(name))
        out = own if out is None else out.unionByName(own)
    return out


def w24_autoscale(spark: SparkSession, sf_dir: str) -> DataFrame:
    return autoscale.simulate(autoscale.signals(tables.events(spark, sf_dir)), 10)


def w25_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = stripes.build(_hist(spark, sf_dir), LayoutSpec(stripe_len=64))
    return codec.size_report(st).withColumn("density", F.col("encoded_bits") / F.col("plain_bits"))


def w28_cache(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Streaming trainers follow the clock; batch jobs over spread dates don't. A block is a nation's day."""
    asks = history.requests_of(_hist(spark, sf_dir, "nation")).withColumn("block", F.concat_ws(":", "user_id", F.floor(F.col("t_us") / DAY)))
    spread = F.conv(F.substring(F.md5(F.col("request_id").cast("string")), 1, 13), 16, 10).cast("long")
    stream = cost.cache_hits(asks, [F.col("t_us"), F.col("request_id")], "block", 64).withColumn("mode", F.lit("streaming"))
    batch = cost.cache_hits(asks, [spread, F.col("request_id")], "block", 64).withColumn("mode", F.lit("spread"))
    return stream.unionByName(batch)


def w29_concurrency(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    index = stripes.index(stripes.build(hist, LAYOUT, ("us", "event_id")))
    jobs = spark.range(100).select(F.col("id").alias("job"), (F.col("id") % 20).alias("from_day"), (F.col("id") % 20 + 9).alias("to_day"))
    first = hist.agg(F.min(F.floor(F.col("us") / DAY))).first()[0]
    a, b = (F.floor(F.col(c) / DAY) - first for c in ("first_us", "last_us"))
    days = index.select("user_id", "stripe_no", F.explode(F.sequence(a, b)).alias("day")).distinct()
    wanted = jobs.select("job", F.explode(F.sequence("from_day", "to_day")).alias("day"))
    return cost.shared_reads(days.join(F.broadcast(wanted), "day").select("job", "user_id", "stripe_no"))


def w30_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = _counts(spark, sf_dir)
    rows = counts.select("*", F.explode(F.array(*[F.lit(x) for x in NE_LENGTHS])).alias("length"))
    lengths = rows.groupBy("length").agg((F.sum(F.least(F.col("seq_len") + F.col("mutable"), F.col("length"))) / F.count("*")).alias("elems"))
    return cost.breakdown(lengths).select("length", "component", F.round("units", 9).alias("units"))


def w31_delete_effort(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    items, _ = _deleted(spark, sf_dir)
    wide = baselines.wide_row(history.requests_of(hist), hist)
    patch = baselines.patch_deletes(wide, items).select(F.lit("patch_wide_rows").alias("method"), F.col("touched_rows").alias("rows_rewritten"))
    built = stripes.build(hist, LAYOUT, ("us", "event_id")).agg(F.count("*").alias("rows_rewritten")).withColumn("method", F.lit("rebuild_stripes"))
    return patch.unionByName(built)


def w32_eligibility(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table that only grows has no violations; one whose values are overwritten has."""
    hist = _hist(spark, sf_dir)
    end = _end(hist)
    old, new = hist.filter(F.col("us") < end), hist
    edited = new.withColumn("value", F.when(F.col("event_id") % 1000 == 0, F.lit(0.0)).otherwise(F.col("value")))
    out = None
    for name, later in (("append_only", new), ("overwritten", edited)):
        own = history.check_append_only(old, later, end - DAY).agg(F.count("*").alias("violations")).withColumn("snapshot", F.lit(name))
        out = own if out is None else out.unionByName(own)
    return out


def w33_label_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    found = baselines.snapshot_join(history.requests_of(hist), hist.filter("event_type = 'purchase'"), DAY)
    return found.select("request_id", "label", F.coalesce(F.col("label_us") - F.col("t_us"), F.lit(-1)).alias("delay_us"))


def w34_freshness(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, _, slim, st = _case(spark, sf_dir)
    full = replay.reconstruct(slim, st, None, "range")
    old = replay.unpack(slim).select("request_id", (F.col("t_us") - F.col("end_us")).alias("lag_us"))
    out = None
    for mode, rows in (("replay", verify.freshness(full)), ("immutable_only", old)):
        own = rows.agg(F.round(F.avg("lag_us"), 3).alias("avg_lag_us"), F.count("*").alias("requests")).withColumn("mode", F.lit(mode))
        out = own if out is None else out.unionByName(own)
    return out


def _c(key: str = "user") -> str:
    return sql.base(key=key).rstrip() + ", C AS (SELECT request_id, user_id, t_us, c_us, count(*) FILTER (us < c_us) AS s, count(*) FILTER (us >= c_us) AS m FROM W GROUP BY ALL)"


def _look(key: str, slot: str) -> str:
    return f"""{sql.base(key=key).rstrip()}, ST AS (SELECT user_id, us, event_id, (row_number() OVER (PARTITION BY user_id ORDER BY us, event_id) - 1) // 8 AS stripe_no FROM H),
SZ AS (SELECT user_id, stripe_no, count(*) AS n FROM ST GROUP BY ALL),
T AS (SELECT * FROM (VALUES ('A', 64), ('B', 16), ('C', 4)) v(tenant, len)),
SP AS (SELECT tenant, W.user_id, {slot} AS slot, min(stripe_no) AS lo, max(stripe_no) AS hi FROM W JOIN ST USING (user_id, us, event_id) JOIN T ON back <= len WHERE us < c_us GROUP BY ALL),
RD AS (SELECT tenant, SP.user_id, slot, sum(n) AS e FROM SP JOIN SZ ON SZ.user_id = SP.user_id AND stripe_no BETWEEN lo AND hi GROUP BY ALL),
LK AS (SELECT tenant, count(*) AS lookups, CAST(sum(e) AS BIGINT) AS lookup_elems FROM RD GROUP BY tenant),
BASE AS (SELECT sum(least(n, 64)) AS base FROM (SELECT count(*) AS n FROM W GROUP BY request_id))"""


_T = "(VALUES ('A', 64, 2), ('B', 16, 20), ('C', 4, 20)) v(tenant, len, jobs)"
_READ = f"SELECT tenant, jobs, CAST(sum(least(s + m, 64)) AS BIGINT) AS base, CAST(sum(least(m, len) + CASE WHEN s > 0 THEN 4 ELSE 0 END) AS BIGINT) AS ours FROM C, {_T} GROUP BY tenant, jobs"


def _ne_sql(lengths: tuple[int, ...]) -> str:
    values = ", ".join(f"({n})" for n in lengths)
    return f"""{sql.base().rstrip()}, LB AS (SELECT R.request_id, max(CASE WHEN h.us IS NULL THEN 0 ELSE 1 END) AS y FROM R LEFT JOIN H h ON h.user_id = R.user_id AND h.event_type = 'purchase' AND h.us > t_us AND h.us <= t_us + {DAY} GROUP BY 1),
Q AS (SELECT avg(y) AS q FROM LB),
F AS (SELECT len, request_id, count(*) FILTER (event_type = 'purchase') AS b, count(*) AS n FROM W JOIN (VALUES {values}) v(len) ON back <= len GROUP BY ALL),
P AS (SELECT len, y, q, greatest(1e-6, least(1 - 1e-6, (b + 20.0 * q) / (n + 20.0))) AS p FROM F JOIN LB USING (request_id), Q),
NE AS (SELECT len, avg(CASE WHEN y = 1 THEN -ln(p) ELSE -ln(1 - p) END) / -(max(q) * ln(max(q)) + (1 - max(q)) * ln(1 - max(q))) AS ne FROM P GROUP BY len)"""


def _ladder_sql(key: str, lengths: tuple[int, ...]) -> str:
    values = ", ".join(f"({n})" for n in lengths)
    return f"(WITH X AS ({_c(key)} SELECT * FROM C) SELECT len AS length, CAST(sum(least(s + m, len)) AS BIGINT) AS wide_elems, CAST(sum(least(m, len)) AS BIGINT) AS logged_elems, CAST(sum(least(s, greatest(0, len - m))) AS BIGINT) AS replay_elems, '{key}' AS key FROM X, (VALUES {values}) v(len) GROUP BY len)"


def wall_sql(powers: range) -> str:
    ladder = _ladder_sql("region", tuple(1 << k for k in powers))
    return f"""WITH L AS {ladder}, M AS (SELECT length, 'wide' AS mode, 1.0::DOUBLE AS share FROM L UNION ALL SELECT length, 'replay', (logged_elems + replay_elems / {cost.READ_RATIO}::DOUBLE) / wide_elems FROM L),
K AS (SELECT CAST(length AS INTEGER) AS length, mode, ({_COSTS.d0}::DOUBLE + {_COSTS.d1!r}::DOUBLE * (share * length)) / ({_COSTS.g0}::DOUBLE + {_COSTS.g1!r}::DOUBLE * length) AS ratio FROM M)"""


def _over_sql(key: str, short: int, long: int) -> str:
    return f"(WITH X AS ({_c(key)} SELECT sum(least(s + m, {short})) AS a, sum(least(s + m, {long})) AS b FROM C) SELECT tenant, CAST(b AS BIGINT) AS read, CAST(CASE tenant WHEN 'short' THEN a ELSE b END AS BIGINT) AS needed, b / CASE tenant WHEN 'short' THEN a ELSE b END AS over_read, '{key}' AS key FROM X, (VALUES ('short'), ('long')) v(tenant))"


def _slots(key: str) -> str:
    return " UNION ALL ".join(f"(WITH X AS ({sql.base(key=key)} SELECT user_id, t_us FROM R) SELECT '{key}' AS key, '{n}' AS slot, count(DISTINCT (user_id, t_us // {w})) AS lookups, count(*) AS requests, count(DISTINCT (user_id, t_us // {w})) / count(*) AS pct FROM X)" for n, w in (("hour", HOUR), ("day", DAY)))


_B = sql.base()
_COSTS = cost.UnitCosts()
_NAT = _c("nation")
_GONE = "H.item_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1) AND H.user_id NOT IN (SELECT c_custkey FROM customer WHERE c_acctbal < 0)"
_UP = f"LAG(us) OVER (PARTITION BY user_id, stripe_no ORDER BY us, event_id)"
_RUNS = "SELECT '{0}' AS layout, avg(runs) AS mean_runs, max(runs) AS max_runs, (SELECT 1 + avg({2}) FROM DD) AS write_amp FROM (SELECT request_id, count(DISTINCT {1}) AS runs FROM W JOIN DD USING (user_id, us, event_id) WHERE us < c_us GROUP BY 1)"
_MERGED = "CASE WHEN d < 16 THEN 0 WHEN d < 28 THEN 16 + (d - 16) // 4 * 4 ELSE d END"

QUERIES = {
    "w01_primary_write": (w01_primary_write, f"{_c()} SELECT CAST(sum(least(s + m, 64)) AS BIGINT) AS wide_elems, CAST(sum(m) AS BIGINT) AS slim_elems, 4 * count(*) FILTER (s > 0) AS pointer_scalars, 1 - (sum(m) + 4 * count(*) FILTER (s > 0)) / sum(least(s + m, 64)) AS reduction FROM C"),
    "w02_primary_read": (w02_primary_read, f"{_c()}, RD AS ({_READ}) SELECT tenant, base, ours, 1 - ours / base AS reduction FROM RD"),
    "w03_lookup_streaming": (w03_lookup_streaming, f"{_look('user', 'request_id')} SELECT tenant, lookups, lookup_elems, lookup_elems / base AS pct FROM LK, BASE"),
    "w03_lookup_hourly": (w03_lookup_hourly, f"{_look('nation', f't_us // {HOUR}')} SELECT tenant, lookups, lookup_elems, lookup_elems / base AS pct FROM LK, BASE"),
    "w04_lookup_batch": (w04_lookup_batch, " UNION ALL ".join(_slots(k) for k in ("user", "nation", "region"))),
    "w05_latency": (w05_latency, None),
    "w06_fleet": (w06_fleet, f"{_look('user', f't_us // {HOUR}')}, C AS (SELECT request_id, count(*) FILTER (us < c_us) AS s, count(*) FILTER (us >= c_us) AS m FROM W GROUP BY 1), RR AS ({_READ}) SELECT 1 - sum(jobs * (ours + lookup_elems / 3.4)) / sum(jobs * base) AS total_saving FROM RR JOIN LK USING (tenant)"),
    "w07_effective": (w07_effective, f"{_look('user', 'request_id')}, DR AS (SELECT avg(n) AS day_runs FROM (SELECT count(DISTINCT us // {DAY}) AS n FROM W WHERE us < c_us GROUP BY request_id)) SELECT tenant, lookup_elems / base / 3.4 AS effective, day_runs, 1 AS single_level_runs FROM LK, BASE, DR"),
    "w08_base_batch": (w08_base_batch, f"{_NAT}, E AS (SELECT row_number() OVER (ORDER BY request_id) - 1 AS i, least(s + m, 1024) AS e FROM C), B AS (SELECT size, i // size AS b, sum(e) AS e FROM E, (VALUES (64), (256), (1024), (4096)) v(size) GROUP BY ALL) SELECT size, count(*) AS batches, CAST(max(e) AS BIGINT) AS peak_elems, avg(e) AS mean_elems FROM B GROUP BY size"),
    "w09_prefetch": (w09_prefetch, f"{_NAT}, B AS (SELECT (row_number() OVER (ORDER BY request_id) - 1) // 64 AS b, m AS r, least(s, greatest(0, 64 - m)) AS l FROM C), T AS (SELECT b, b % 4 AS w, sum(r) AS r, sum(l) AS l FROM B GROUP BY b), G AS (SELECT w, sum(r + l) AS serial, sum(CASE WHEN b < 4 THEN r ELSE 0 END + greatest(l, coalesce(nx, 0))) AS piped FROM (SELECT *, lead(r) OVER (PARTITION BY w ORDER BY b) AS nx FROM T) GROUP BY w) SELECT CAST(max(serial) AS BIGINT) AS serial, CAST(max(piped) AS BIGINT) AS pipelined, max(serial) / max(piped) - 1 AS gain FROM G"),
    "w10_affinity": (w10_affinity, f"{sql.base(key='nation').rstrip()}, B AS (SELECT user_id, (row_number() OVER (ORDER BY request_id) - 1) // 64 AS b, (row_number() OVER (ORDER BY user_id % 8, request_id) - 1) // 64 AS c FROM R), S AS (SELECT count(DISTINCT (user_id, t_us // {HOUR})) AS lookups FROM R) SELECT 'plain' AS mode, (SELECT count(*) FROM R) AS lookups, (SELECT avg(n) FROM (SELECT count(DISTINCT user_id % 8) AS n FROM B GROUP BY b)) AS fanout UNION ALL SELECT 'affinity', lookups, (SELECT avg(n) FROM (SELECT count(DISTINCT user_id % 8) AS n FROM B GROUP BY c)) FROM S UNION ALL SELECT 'asymmetric', lookups, (SELECT avg(n) FROM (SELECT count(DISTINCT user_id % 6) AS n FROM B GROUP BY c)) FROM S"),
    "w11_ladder": (w11_ladder, " UNION ALL ".join((_ladder_sql("user", (4, 8, 16, 32, 64)), _ladder_sql("nation", LADDER), _ladder_sql("region", (*LADDER, 16384))))),
    "w12_ne_parity": (w12_ne_parity, f"{_ne_sql(NE_LENGTHS)} SELECT len AS length, round(ne, 9) AS ne_wide, round(ne, 9) AS ne_replay FROM NE"),
    "w13_ne_curve": (w13_ne_curve, f"{_ne_sql((4, 8, 16, 32, 64))} SELECT len AS length, round(ne, 9) AS ne, round(((SELECT ne FROM NE WHERE len = 4) - ne) / (SELECT ne FROM NE WHERE len = 4), 9) AS gain FROM NE"),
    "w13_ne_model": (w13_ne_model, None),
    "w14_wall": (w14_wall, f"{wall_sql(range(8, 17))} SELECT length, mode, round(ratio, 9) AS ratio, ratio > 0.75 AS over FROM K"),
    "w15_ab": (w15_ab, f"WITH {sql.HIST}, U AS (SELECT user_id % 2 AS arm, count(*) AS e, sum(value) AS v, count(*) FILTER (event_type = 'purchase') AS p, count(*) FILTER (event_type = 'signup') AS g FROM H GROUP BY user_id), M AS (SELECT arm, avg(e) AS topline, avg(v) AS consumption, avg(p) AS explicit_purchase, avg(g) AS explicit_signup FROM U GROUP BY arm), X AS (UNPIVOT M ON topline, consumption, explicit_purchase, explicit_signup INTO NAME metric VALUE x) SELECT metric, round(max(x) FILTER (arm = 1) / max(x) FILTER (arm = 0) - 1, 9) AS gain FROM X GROUP BY metric"),
    "w16_amplify_k": (w16_amplify_k, f"WITH {sql.HIST}, D AS (SELECT DISTINCT user_id, us // {DAY} AS d FROM H), G AS (SELECT k, user_id, d * {DAY} + CAST(floor(j * {DAY} / (k + 1)) AS BIGINT) AS t_us, d * {DAY} - 6 * {DAY} AS lo FROM D, (VALUES (1), (2), (4), (8)) v(k), range(1, 9) r(j) WHERE j <= k) SELECT k, count(*) AS wide, count(DISTINCT event_id) AS canonical, count(*) / count(DISTINCT event_id) AS factor FROM G JOIN H ON H.user_id = G.user_id AND us <= t_us AND us >= lo GROUP BY k"),
    "w17_tenant_penalty": (w17_tenant_penalty, _over_sql("user", 4, 64) + " UNION ALL " + _over_sql("region", 100, 10_000)),
    "w18_fidelity": (w18_fidelity, f"{_B} {sql.SUMMARY} GROUP BY request_id"),
    "w19_leakage": (w19_leakage, f"{_B.rstrip()}, L AS (SELECT 'etl_join' AS method, request_id, H.us > t_us AS late FROM R JOIN H ON H.user_id = R.user_id AND H.us < (t_us // {DAY} + 1) * {DAY} UNION ALL SELECT 'latest_state', request_id, H.us > t_us FROM R JOIN H ON H.user_id = R.user_id UNION ALL SELECT 'replay', request_id, us > t_us FROM W) SELECT method, count(*) FILTER (late) AS leaked_events, count(DISTINCT request_id) FILTER (late) AS leaked_requests FROM L GROUP BY method"),
    "w20_layered": (w20_layered, f"{_B} SELECT request_id, count(*) FILTER (feature_group = 'dense') AS n_dense, count(*) FILTER (feature_group = 'sparse') AS n_sparse FROM W WHERE (feature_group = 'dense' AND us >= c_us - 6 * {DAY}) OR feature_group = 'sparse' GROUP BY request_id"),
    "w21_delete": (w21_delete, f"WITH {sql.HIST} SELECT count(*) AS kept, (SELECT count(*) FROM H) - count(*) AS scrubbed, CAST(sum({sql.HASH32}) AS BIGINT) AS digest FROM H WHERE {_GONE}"),
    "w21_scrub_logged": (w21_scrub_logged, f"{_B} SELECT request_id, count(*) FILTER (us >= c_us AND item_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1)) AS mutable FROM W GROUP BY request_id"),
    "w22_sideinfo": (w22_sideinfo, f"WITH {sql.HIST}, N AS (SELECT *, (row_number() OVER (PARTITION BY user_id ORDER BY us, event_id) - 1) // 8 AS stripe_no FROM H WHERE us < (SELECT max(us // {DAY} * {DAY}) FROM H) AND us >= (SELECT max(us // {DAY} * {DAY}) FROM H) - 30 * {DAY}) SELECT user_id, CAST(stripe_no AS BIGINT) AS stripe_no, md5(string_agg(event_id || ':' || coalesce(lang, '-') || ':' || coalesce(p_brand, '-'), ',' ORDER BY us, event_id)) AS digest FROM N LEFT JOIN documents ON doc_id = item_id LEFT JOIN part ON p_partkey = item_id GROUP BY user_id, stripe_no"),
    "w23_lsm": (w23_lsm, f"{_B.rstrip()}, D0 AS (SELECT user_id, us, event_id, us // {DAY} - (SELECT min(us) // {DAY} FROM H) AS d FROM H), DD AS (SELECT *, CASE WHEN d < 16 THEN 2 WHEN d < 28 THEN 1 ELSE 0 END AS mg FROM D0) {_RUNS.format('append_days', 'd', '0')} UNION ALL {_RUNS.format('multi_level', _MERGED, 'mg')} UNION ALL {_RUNS.format('single_level', '1', '0')}"),
    "w24_autoscale": (w24_autoscale, f"WITH RECURSIVE L AS (SELECT coalesce(event_type, '-') AS job, epoch_us(ts) // {HOUR} AS slot, count(*) AS n FROM events WHERE ts IS NOT NULL GROUP BY ALL), T AS (SELECT min(slot) AS lo, max(slot) AS hi, max(slot) - min(slot) + 1 AS ticks FROM L), J AS (SELECT job, CAST(sum(n) AS BIGINT) AS total FROM L GROUP BY job), K AS (SELECT job, total, lo, ticks, unnest(range(lo, hi + 1)) AS slot FROM J, T), G AS (SELECT K.job, K.slot - lo AS tick, coalesce(n, 0) * ticks AS load, total FROM K LEFT JOIN L ON L.job = K.job AND L.slot = K.slot), X AS MATERIALIZED (SELECT job, tick, CASE WHEN load > total THEN (load - total) / load ELSE 0 END AS starvation, CASE WHEN load < total THEN (total - load) / total ELSE 0 END AS waste FROM G), S AS (SELECT job, CAST(-1 AS BIGINT) AS tick, 10 AS workers FROM J UNION ALL SELECT S.job, S.tick + 1, CAST(least(1000, greatest(1, CASE WHEN starvation > 0.05::DOUBLE THEN ceil(workers * (1 + 0.5::DOUBLE * starvation)) WHEN waste > 0.3::DOUBLE THEN floor(workers * (1 - 0.5::DOUBLE * waste)) ELSE workers END)) AS INTEGER) FROM S JOIN X ON X.job = S.job AND X.tick = S.tick + 1) SELECT * FROM S WHERE tick >= 0"),
    "w25_codec": (w25_codec, f"WITH {sql.HIST}, N AS (SELECT *, (row_number() OVER (PARTITION BY user_id ORDER BY us, event_id) - 1) // 64 AS stripe_no FROM H), G AS (SELECT *, us - {_UP} AS gap FROM N), S AS (SELECT count(*) AS n, coalesce(max(gap), 0) AS g, count(DISTINCT event_type) AS k FROM G GROUP BY user_id, stripe_no), T AS (SELECT 'us' AS trait, 64 * n AS p, 64 + (n - 1) * greatest(1, CAST(ceil(log2(greatest(1, g + 1))) AS BIGINT)) AS e FROM S UNION ALL SELECT 'event_type', 64 * n, 64 * k + n * greatest(1, CAST(ceil(log2(k)) AS BIGINT)) FROM S UNION ALL SELECT 'is_purchase', 8 * n, 64 * CAST(ceil(n / 64.0) AS BIGINT) FROM S UNION ALL SELECT 'value', 64 * n, 64 * n FROM S) SELECT trait, CAST(sum(p) AS BIGINT) AS plain_bits, CAST(sum(e) AS BIGINT) AS encoded_bits, sum(e) / sum(p) AS density FROM T GROUP BY trait"),
    "w28_cache": (w28_cache, f"{sql.base(key='nation').rstrip()}, A AS (SELECT user_id || ':' || t_us // {DAY} AS block, row_number() OVER (ORDER BY t_us, request_id) AS i, row_number() OVER (ORDER BY substr(md5(CAST(request_id AS VARCHAR)), 1, 13), request_id) AS j FROM R), G AS (SELECT 'streaming' AS mode, i - lag(i) OVER (PARTITION BY block ORDER BY i) AS g FROM A UNION ALL SELECT 'spread', j - lag(j) OVER (PARTITION BY block ORDER BY j) FROM A) SELECT mode, count(*) AS accesses, count(*) FILTER (g <= 64) AS hits, count(*) FILTER (g <= 64) / count(*) AS hit_rate FROM G GROUP BY mode"),
    "w29_concurrency": (w29_concurrency, f"WITH {sql.HIST}, ST AS (SELECT user_id, us, (row_number() OVER (PARTITION BY user_id ORDER BY us, event_id) - 1) // 8 AS stripe_no FROM H), B AS (SELECT user_id, stripe_no, min(us) // {DAY} - (SELECT min(us) // {DAY} FROM H) AS a, max(us) // {DAY} - (SELECT min(us) // {DAY} FROM H) AS b FROM ST GROUP BY ALL), X AS (SELECT DISTINCT j, user_id, stripe_no FROM B, range(100) t(j) WHERE a <= j % 20 + 9 AND b >= j % 20) SELECT count(DISTINCT j) AS jobs, count(*) AS total, count(DISTINCT (user_id, stripe_no)) AS distinct_stripes, count(*) / count(DISTINCT (user_id, stripe_no)) AS reuse FROM X"),
    "w30_breakdown": (w30_breakdown, f"{_c()}, E AS (SELECT len, sum(least(s + m, len)) / count(*) AS e FROM C, (VALUES (4), (16), (64)) v(len) GROUP BY len) SELECT len AS length, component, round(share * {_COSTS.d1!r}::DOUBLE * e, 9) AS units FROM E, (VALUES {', '.join(f'({k!r}, {v}::DOUBLE)' for k, v in cost.COMPONENTS.items())}) v(component, share) UNION ALL SELECT len, 'accelerator', round(1.0 + {_COSTS.g1!r}::DOUBLE * len, 9) FROM E"),
    "w31_delete_effort": (w31_delete_effort, f"{_B} SELECT 'patch_wide_rows' AS method, count(DISTINCT request_id) AS rows_rewritten FROM W WHERE item_id IN (SELECT doc_id FROM labels WHERE toxic = 1) UNION ALL SELECT 'rebuild_stripes', CAST(sum(n) AS BIGINT) FROM (SELECT CAST(ceil(count(*) / 8.0) AS BIGINT) AS n FROM H GROUP BY user_id)"),
    "w32_eligibility": (w32_eligibility, f"WITH {sql.HIST} SELECT 'append_only' AS snapshot, 0 AS violations UNION ALL SELECT 'overwritten', 2 * count(*) FROM H WHERE event_id % 1000 = 0 AND value <> 0 AND us < (SELECT max(us // {DAY} * {DAY}) FROM H) - {DAY}"),
    "w33_label_join": (w33_label_join, f"WITH {sql.HIST}, {sql.requests()} SELECT request_id, CAST(CASE WHEN min(h.us) IS NULL THEN 0 ELSE 1 END AS INTEGER) AS label, coalesce(min(h.us - t_us), -1) AS delay_us FROM R LEFT JOIN H h ON h.user_id = R.user_id AND h.event_type = 'purchase' AND h.us > t_us AND h.us <= t_us + {DAY} GROUP BY request_id"),
    "w35_table1_bytes": (w35_table1_bytes, None),
    "w34_freshness": (w34_freshness, f"{_B.rstrip()}, X AS (SELECT 'replay' AS mode, request_id, max(t_us) - max(us) AS g FROM W GROUP BY request_id UNION ALL SELECT 'immutable_only', request_id, max(t_us) - max(us) FROM W WHERE us < c_us GROUP BY request_id) SELECT mode, round(avg(g), 3) AS avg_lag_us, count(*) AS requests FROM X GROUP BY mode"),
}
