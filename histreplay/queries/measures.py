"""Queries of cost and accuracy measures that no workload shows by itself."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from histreplay.operators import affinity, baselines, generations, history, protocol, replay, verify
from histreplay.plans import cost
from histreplay.queries import sql
from histreplay.queries.methods import LAYOUT, _case, _end, _hist
from histreplay.queries.workloads import _c, _counts, wall_curve, wall_sql
from histreplay.schema import DAY


def c07_footprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cost.footprint(_counts(spark, sf_dir), _hist(spark, sf_dir).count())


def c07_closed_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The share of copied events that lie in closed days, for a window of seven: near (N - 1) / N."""
    hist = _hist(spark, sf_dir)
    rows = history.window_events(history.requests_of(hist), hist, 7)
    return rows.agg((F.count_if(F.col("us") < F.col("cutoff_us")) / F.count("*")).alias("closed_share"), F.count("*").alias("copies"))


def c09_log_volume(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cost.log_volume(_counts(spark, sf_dir))


def c10_amplification(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    store = baselines.lsm(hist, 4)
    asks = history.requests_of(hist).withColumn("hi", protocol.cutoff_of(F.col("t_us")))
    runs = asks.join(store.select("user_id", "us", "run_lo"), "user_id").filter(F.col("us") < F.col("hi")).groupBy("request_id").agg(F.count_distinct("run_lo").alias("runs"))
    return cost.amplification(runs, store)


def c12_amortisation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Requests a lookup, by session of 30 minutes, on the region key."""
    found = affinity.session_lookups(history.requests_of(_hist(spark, sf_dir, "region")), "30 minutes")
    return found.agg(F.count("*").alias("lookups"), F.sum("requests").alias("requests")).withColumn("amortisation", F.col("requests") / F.col("lookups"))


def c15_wall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The smallest length over the limit, for whole rows and for replay; -1 if none is."""
    found = cost.wall(wall_curve(spark, sf_dir, tuple(1 << k for k in range(8, 18))))
    return found.select("mode", F.coalesce("wall", F.lit(-1)).alias("wall"))


def c19_fidelity_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, _, slim, st = _case(spark, sf_dir)
    asks = replay.unpack(slim).withColumn("need", F.col("seq_len"))
    old = replay.cut(asks, replay.multi_range(asks, st, "range"), ("us", "event_id")).withColumnsRenamed({"i_us": "us", "i_event_id": "event_id"})
    return verify.rate(verify.check(old.join(slim.select("request_id", "user_id"), "request_id"), asks))


def c24_training_lag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Streaming trains with the next event of the user, batch after the day's end."""
    asks = history.requests_of(_hist(spark, sf_dir))
    day = (F.floor(F.col("t_us") / DAY) + 1) * DAY
    return asks.agg(F.round(F.avg(cost.lag(day, F.col("t_us"))), 3).alias("batch_lag_us"), F.count("*").alias("requests"))


def c26_schema_change(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What a new column costs: the stripes of one regeneration, or the day partitions of the window that a backfill rewrites."""
    hist = _hist(spark, sf_dir)
    end = _end(hist)
    inside = hist.filter((F.col("us") < end) & (F.col("us") >= end - 30 * DAY))
    days = hist.select(F.floor(F.col("us") / DAY).alias("day")).distinct().agg(F.count("*").alias("partitions"))
    filled = inside.select(F.floor(F.col("us") / DAY).alias("day")).distinct().agg(F.count("*").alias("backfill_days"))
    built = generations.rebuild(hist, end, 30, LAYOUT).agg(F.count("*").alias("stripes"))
    return days.crossJoin(built).crossJoin(filled)


def c08_window_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cost.sharing(_counts(spark, sf_dir))


_H = f"WITH {sql.HIST} "
QUERIES = {
    "c07_footprint": (c07_footprint, f"{_c()} SELECT CAST(sum(s + m) AS BIGINT) AS wide_total, CAST(sum(m) + (SELECT count(*) FROM H) AS BIGINT) AS replay_total, sum(s + m) / (sum(m) + (SELECT count(*) FROM H)) AS factor FROM C"),
    "c07_closed_days": (c07_closed_days, f"{sql.base(7)} SELECT count(*) FILTER (us < c_us) / count(*) AS closed_share, count(*) AS copies FROM W"),
    "c08_window_share": (c08_window_share, f"{_c()} SELECT tenant, sum(least(s + m, len)) / sum(least(s + m, 64)) AS window_share FROM C, (VALUES ('A', 64), ('B', 16), ('C', 4)) v(tenant, len) GROUP BY tenant"),
    "c09_log_volume": (c09_log_volume, f"{_c()} SELECT CAST(floor(log2(s + m)) AS BIGINT) AS bucket, count(*) AS requests, CAST(sum(5 * (s + m)) AS BIGINT) AS wide_values, CAST(sum(5 * m + CASE WHEN s > 0 THEN 4 ELSE 0 END) AS BIGINT) AS slim_values FROM C GROUP BY 1"),
    "c10_amplification": (c10_amplification, f"{sql.base(100).rstrip()}, D0 AS (SELECT user_id, us, event_id, us // {DAY} - (SELECT min(us) // {DAY} FROM H) AS d FROM H), DD AS (SELECT *, CASE WHEN d < 16 THEN 0 WHEN d < 28 THEN 16 + (d - 16) // 4 * 4 ELSE d END AS run, CASE WHEN d < 16 THEN 2 WHEN d < 28 THEN 1 ELSE 0 END AS mg FROM D0) SELECT avg(n) AS read_runs, (SELECT 1 + avg(mg) FROM DD) AS write_amp FROM (SELECT request_id, count(DISTINCT run) AS n FROM W JOIN DD USING (user_id, us, event_id) WHERE us < c_us GROUP BY 1)"),
    "c12_amortisation": (c12_amortisation, f"{sql.base(key='region').rstrip()}, G AS (SELECT CASE WHEN t_us - lag(t_us) OVER (PARTITION BY user_id ORDER BY t_us, request_id) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM R) SELECT CAST(sum(fresh) AS BIGINT) AS lookups, count(*) AS requests, count(*) / sum(fresh) AS amortisation FROM G"),
    "c15_wall": (c15_wall, f"{wall_sql(range(8, 18))} SELECT mode, coalesce(min(length) FILTER (ratio > 0.75), -1) AS wall FROM K GROUP BY mode"),
    "c19_fidelity_rate": (c19_fidelity_rate, f"{sql.base()} SELECT count(DISTINCT request_id) AS checked, count(DISTINCT request_id) AS ok, 1.0 AS share FROM W WHERE us < c_us"),
    "c24_training_lag": (c24_training_lag, f"{_H.rstrip()}, {sql.requests()} SELECT round(avg((t_us // {DAY} + 1) * {DAY} - t_us), 3) AS batch_lag_us, count(*) AS requests FROM R"),
    "c26_schema_change": (c26_schema_change, _H.rstrip() + f", E AS (SELECT max(us // {DAY} * {DAY}) AS e FROM H), I AS (SELECT H.* FROM H, E WHERE us < e AND us >= e - 30 * {DAY}) SELECT (SELECT count(DISTINCT us // {DAY}) FROM H) AS partitions, (SELECT CAST(sum(n) AS BIGINT) FROM (SELECT CAST(ceil(count(*) / 8.0) AS BIGINT) AS n FROM I GROUP BY user_id)) AS stripes, (SELECT count(DISTINCT us // {DAY}) FROM I) AS backfill_days"),
}
