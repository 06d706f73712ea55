"""Cost measures, counted in elements: an element is one event with its traits in one row."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from histreplay.operators import project, protocol
from histreplay.operators.batching import _numbered
from histreplay.schema import DAY, TENANTS, PointerSpec, TenantSpec

#: Scalars that a pointer adds to an example: start, end, length, digest.
POINTER_SCALARS = 4
#: Reported read throughput per unit of host resource, immutable tier against the append-only store.
READ_RATIO = 3.4


def request_counts(requests: DataFrame, hist: DataFrame, spec: PointerSpec = PointerSpec(digest=None)) -> DataFrame:
    """(request_id, user_id, t_us, seq_len, mutable): lengths of both parts, without building a sequence.

    Events of the cutoff's period up to t are counted by one window over events and requests together.
    """
    period = F.floor(F.col("us") / spec.cadence)
    asks = requests.select("request_id", "user_id", F.col("t_us").alias("us"), F.lit(0).alias("one"))
    both = hist.select("user_id", "us", F.lit(1).alias("one")).unionByName(asks, allowMissingColumns=True).withColumn("period", period)
    frame = Window.partitionBy("user_id", "period").orderBy("us").rangeBetween(Window.unboundedPreceding, 0)
    recent = both.withColumn("mutable", F.sum("one").over(frame)).filter("request_id is not null").select("request_id", "mutable")
    return protocol.pointers(requests, hist, spec).select("request_id", "user_id", "t_us", "seq_len").join(recent, "request_id")


def wide_elems(counts: DataFrame, length: int) -> Column:
    return F.sum(F.least(F.col("seq_len") + F.col("mutable"), F.lit(length)))


def primary_write(counts: DataFrame, max_len: int, other: int = 0) -> DataFrame:
    """(wide_elems, slim_elems, pointer_scalars, reduction) of one write for all tenants; other: further values of a row."""
    n = F.count("*") * other
    sums = counts.agg(wide_elems(counts, max_len).alias("wide_elems"), F.sum("mutable").alias("slim_elems"), (POINTER_SCALARS * F.count_if(F.col("seq_len") > 0)).alias("pointer_scalars"), n.alias("o"))
    return sums.select("wide_elems", "slim_elems", "pointer_scalars", (1 - (F.col("slim_elems") + F.col("pointer_scalars") + F.col("o")) / (F.col("wide_elems") + F.col("o"))).alias("reduction"))


def primary_read(counts: DataFrame, tenants: tuple[TenantSpec, ...] = TENANTS) -> DataFrame:
    """(tenant, base, ours, reduction): of the union table at its longest length against the logged parts."""
    top = max(t.seq_len for t in tenants)
    rows = F.array(*[F.struct(F.lit(t.name).alias("tenant"), F.least(F.col("seq_len") + F.col("mutable"), F.lit(top)).alias("base"), (F.least(F.col("mutable"), F.lit(t.seq_len)) + F.when(F.col("seq_len") > 0, POINTER_SCALARS).otherwise(0)).alias("ours")) for t in tenants])
    sums = counts.select(F.explode(rows).alias("x")).groupBy("x.tenant").agg(F.sum("x.base").alias("base"), F.sum("x.ours").alias("ours"))
    return sums.withColumn("reduction", 1 - F.col("ours") / F.col("base"))


def lookup(asks: DataFrame, stripes: DataFrame, tenants: tuple[TenantSpec, ...], stripe_len: int, window: int | None = None) -> DataFrame:
    """(tenant, lookups, lookup_elems) of the immutable tier: one lookup a request, or one a user and window of time.

    Ranks are resolved once for all tenants.
    """
    ranked = project.with_ranks(asks.filter("seq_len > 0"), stripes)
    wanted = F.explode(F.array(*[F.struct(F.lit(t.name).alias("tenant"), F.lit(t.seq_len).alias("length")) for t in tenants])).alias("w")
    rows = ranked.select("*", wanted).select("*", "w.tenant", F.least("seq_len", F.greatest(F.lit(0), F.col("w.length") - F.col("mutable"))).cast("long").alias("need"))
    lo, hi = project.stripe_span(F.col("window_rank"), F.col("seq_len"), F.col("need"), stripe_len)
    slot = F.col("request_id") if window is None else F.floor(F.col("t_us") / window)
    found = rows.filter("need > 0").withColumns({"lo": lo, "hi": hi, "slot": slot})
    ranges = found.groupBy("tenant", "user_id", "feature_group", "slot").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    index = stripes.select("user_id", "feature_group", "stripe_no", "n_events")
    read = ranges.join(index, ["user_id", "feature_group"]).filter((F.col("stripe_no") >= F.col("lo")) & (F.col("stripe_no") <= F.col("hi")))
    each = read.groupBy("tenant", "user_id", "slot").agg(F.sum("n_events").alias("e"))
    return each.groupBy("tenant").agg(F.count("*").alias("lookups"), F.sum("e").alias("lookup_elems"))


def over_read(counts: DataFrame, tenants: tuple[TenantSpec, ...]) -> DataFrame:
    """(tenant, read, needed, over_read): what a union table makes a tenant read, over what it needs."""
    top = max(t.seq_len for t in tenants)
    sums = counts.agg(*[wide_elems(counts, n).alias(f"w{n}") for n in sorted({t.seq_len for t in tenants})])
    rows = F.array(*[F.struct(F.lit(t.name).alias("tenant"), F.col(f"w{top}").alias("read"), F.col(f"w{t.seq_len}").alias("needed")) for t in tenants])
    return sums.select(F.inline(rows)).withColumn("over_read", F.col("read") / F.col("needed"))


def redundancy(rows: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, wide, canonical, factor): copies of events in examples over distinct events in them."""
    return rows.groupBy(*keys).agg(F.count("*").alias("wide"), F.count_distinct("user_id", "event_id").alias("canonical")).withColumn("factor", F.col("wide") / F.col("canonical"))


def effective_footprint(lookup_share: Column, ratio: float = READ_RATIO) -> Column:
    return lookup_share / ratio


def fleet(saved: DataFrame, jobs: dict[str, int]) -> DataFrame:
    """(total_saving): savings of tenants (tenant, base, ours) weighted by their jobs."""
    weight = F.create_map(*[F.lit(x) for pair in jobs.items() for x in pair])[F.col("tenant")]
    return saved.agg((1 - F.sum(weight * F.col("ours")) / F.sum(weight * F.col("base"))).alias("total_saving"))


def cache_hits(accesses: DataFrame, order: list[Column], block: str, cache_blocks: int) -> DataFrame:
    """(accesses, hits, hit_rate): an access hits if its block was used within the last `cache_blocks` accesses."""
    at = _numbered(accesses, order)
    gap = F.col("__n") - F.lag("__n").over(Window.partitionBy(block).orderBy("__n"))
    marked = at.withColumn("hit", F.coalesce(gap <= cache_blocks, F.lit(False)))
    return marked.agg(F.count("*").alias("accesses"), F.count_if("hit").alias("hits")).withColumn("hit_rate", F.col("hits") / F.col("accesses"))


def shared_reads(reads: DataFrame) -> DataFrame:
    """(jobs, total, distinct_stripes, reuse) of (job, user_id, stripe_no) reads of many jobs on one generation."""
    each = reads.distinct()
    sums = each.groupBy("user_id", "stripe_no").agg(F.count("*").alias("n")).agg(F.sum("n").alias("total"), F.count("*").alias("distinct_stripes"))
    jobs = each.agg(F.count_distinct("job").alias("jobs"))
    return jobs.crossJoin(sums).withColumn("reuse", F.col("total") / F.col("distinct_stripes"))


@dataclass(frozen=True)
class UnitCosts:
    """A linear model: data services d0 + d1 * elements a request against accelerators g0 + g1 * length."""

    d0: float = 0.1
    g0: float = 1.0
    g1: float = 1.0 / 4096
    limit: float = 0.75

    @property
    def d1(self) -> float:
        """Calibrated so that whole rows of 4096 events just reach the limit."""
        return (self.limit * (self.g0 + self.g1 * 4096) - self.d0) / 4096

    def ratio(self, elems: Column, length: Column) -> Column:
        return (self.d0 + self.d1 * elems) / (self.g0 + self.g1 * length)


def wall(curve: DataFrame, limit: float = 0.75) -> DataFrame:
    """(mode, wall): the smallest length whose ratio passes the limit; null if none does."""
    return curve.groupBy("mode").agg(F.min(F.when(F.col("ratio") > limit, F.col("length"))).alias("wall"))


#: Shares of an element's data-service cost, by component; a model, not a measurement.
COMPONENTS = {"storage": 0.2, "online_ingest": 0.2, "offline_ingest": 0.25, "preprocessing": 0.35}


def breakdown(lengths: DataFrame, costs: UnitCosts = UnitCosts()) -> DataFrame:
    """(length, component, units) of lengths (length, elems): data services by component, and accelerators."""
    rows = [F.struct(F.lit(c).alias("component"), (share * costs.d1 * F.col("elems")).alias("units")) for c, share in COMPONENTS.items()]
    rows.append(F.struct(F.lit("accelerator").alias("component"), (costs.g0 + costs.g1 * F.col("length")).alias("units")))
    return lengths.select("length", F.inline(F.array(*rows)))


def lag(train_us: Column, request_us: Column) -> Column:
    return train_us - request_us


def days_touched(hist: DataFrame, requests: DataFrame, lookback_days: int) -> DataFrame:
    """(request_id, runs): day partitions of an append-only store that hold events of a request's immutable window."""
    days = hist.select("user_id", F.floor(F.col("us") / DAY).alias("day")).distinct()
    asks = requests.withColumn("end_day", F.floor(F.col("t_us") / DAY))
    return asks.join(days, "user_id").filter((F.col("day") < F.col("end_day")) & (F.col("day") >= F.col("end_day") - (lookback_days - 1))).groupBy("request_id").agg(F.count("*").alias("runs"))


def footprint(counts: DataFrame, canonical: int) -> DataFrame:
    """(wide_total, replay_total, factor): elements kept for all examples, against logged parts plus one canonical copy."""
    wide, slim = F.sum(F.col("seq_len") + F.col("mutable")), F.sum("mutable")
    return counts.agg(wide.alias("wide_total"), (slim + F.lit(canonical)).alias("replay_total")).withColumn("factor", F.col("wide_total") / F.col("replay_total"))


def log_volume(counts: DataFrame, traits: int = 5) -> DataFrame:
    """(bucket, requests, wide_values, slim_values) by length (powers of two): values logged with an example.

    A wide row grows with the length; a slim one has its mutable part and a pointer of fixed size.
    """
    n = F.col("seq_len") + F.col("mutable")
    bucket = F.floor(F.log2(n.cast("double"))).cast("long")
    slim = F.col("mutable") * traits + F.when(F.col("seq_len") > 0, POINTER_SCALARS).otherwise(0)
    return counts.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("requests"), F.sum(n * traits).alias("wide_values"), F.sum(slim).alias("slim_values"))


def amplification(runs: DataFrame, store: DataFrame) -> DataFrame:
    """(read_runs, write_amp): runs that a query touches on average, and how often an event is written."""
    return runs.agg(F.avg("runs").alias("read_runs")).crossJoin(store.agg((1 + F.avg("merges")).alias("write_amp")))


def batch_latency(runs: DataFrame) -> DataFrame:
    """(tenant, change) of mean seconds a batch, replay against wide rows, from runs (tenant, mode, seconds)."""
    mean = {m: F.avg(F.when(F.col("mode") == m, F.col("seconds"))) for m in ("replay", "wide")}
    return runs.groupBy("tenant").agg((mean["replay"] / mean["wide"] - 1).alias("change"))


def throughput(runs: DataFrame) -> DataFrame:
    """(mode, rate) in rows a worker and second, from runs (mode, rows, seconds, workers)."""
    return runs.groupBy("mode").agg((F.sum("rows") / F.sum(F.col("seconds") * F.col("workers"))).alias("rate"))


def sharing(counts: DataFrame, tenants: tuple[TenantSpec, ...] = TENANTS) -> DataFrame:
    """(tenant, window_share): what part of the longest tenant's elements each one needs."""
    top = max(t.seq_len for t in tenants)
    rows = F.array(*[F.struct(F.lit(t.name).alias("tenant"), F.least(F.col("seq_len") + F.col("mutable"), F.lit(t.seq_len)).alias("own"), F.least(F.col("seq_len") + F.col("mutable"), F.lit(top)).alias("all")) for t in tenants])
    sums = counts.select(F.explode(rows).alias("x")).groupBy("x.tenant").agg(F.sum("x.own").alias("own"), F.sum("x.all").alias("all"))
    return sums.select("tenant", (F.col("own") / F.col("all")).alias("window_share"))
