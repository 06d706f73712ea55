"""Queries that run as streams over the events, split into files by day, with availableNow."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from histreplay.operators import history, protocol, stripes
from histreplay.queries import sql
from histreplay.queries.methods import LAYOUT, _hist
from histreplay.schema import DAY, HOUR
from histreplay.sources import tables
from histreplay.sources.scratch import folder
from histreplay.streaming import ingest, replay, state


def _dir(spark: SparkSession, name: str) -> str:
    return f"{folder(spark)}/{name}-{uuid.uuid4().hex}"


def _days(spark: SparkSession, sf_dir: str, repeat: bool = False) -> tuple[DataFrame, str]:
    """Events as a folder of files, one a day in time order; with repeat, one event in 100 comes twice."""
    ev = tables.events(spark, sf_dir).select("user_id", "us", "event_id", "event_type", "value", "props")
    if repeat:
        ev = ev.unionByName(ev.filter("event_id % 100 = 0"))
    path = _dir(spark, "events")
    ev.repartitionByRange(8, "us").sortWithinPartitions("us").write.parquet(path)
    return spark.read.parquet(path), path


def _through(spark: SparkSession, out: DataFrame, mode: str = "append") -> DataFrame:
    path = _dir(spark, "result")
    ingest.to_table(out, path, _dir(spark, "checkpoint"), mode=mode)
    return spark.read.schema(out.schema).parquet(path).select(*out.columns)


def _stream(spark: SparkSession, sf_dir: str, repeat: bool = False) -> DataFrame:
    like, path = _days(spark, sf_dir, repeat)
    return ingest.source(spark, path, like, files=2)


def w26_stream_hourly(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = _dir(spark, "hours")
    ingest.hourly(_stream(spark, sf_dir), path, _dir(spark, "checkpoint"))
    return spark.read.parquet(path).groupBy(F.col("hour").cast("long").alias("hour")).agg(F.count("*").alias("n"))


def w27_stream_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    slim_path, stripe_path, out = (_dir(spark, n) for n in ("slim", "stripes", "replayed"))
    protocol.snapshot(history.requests_of(hist), hist).repartition(4).write.parquet(slim_path)
    stripes.build(hist, LAYOUT).write.parquet(stripe_path)
    slim = spark.read.parquet(slim_path)
    replay.run(ingest.source(spark, slim_path, slim, files=2), spark.read.parquet(stripe_path), out, _dir(spark, "checkpoint"))
    return spark.read.parquet(out).select("request_id", "n", "first_us", "last_us", "digest")


def s_tumble(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _through(spark, ingest.tumbling(_stream(spark, sf_dir), "6 hours", "40 days"), "update").groupBy("from_us", "event_type").agg(F.max("n").alias("n"))


def s_slide(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = _through(spark, ingest.sliding(_stream(spark, sf_dir), "1 day", "12 hours", "40 days"), "update")
    return found.groupBy("from_us").agg(F.max("n").alias("n"))


def s_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions that the watermark has closed: those that ended two hours or more before the last event."""
    found = _through(spark, ingest.sessions(_stream(spark, sf_dir), "30 minutes", "1 hour"))
    return found.groupBy("n").agg(F.count("*").alias("sessions"))


def s_dedupe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _through(spark, ingest.deduped(_stream(spark, sf_dir, True).select("user_id", "us", "event_id"), "40 days")).groupBy("user_id").agg(F.count("*").alias("n"))


def s_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = tables.events(spark, sf_dir)
    seen = ev.agg(F.max("us")).first()[0]
    parts = zip(("in_time", "late"), ingest.split_late(ev, seen, 10 * DAY))
    both = [df.agg(F.count("*").alias("n")).withColumn("part", F.lit(p)) for p, df in parts]
    return both[0].unionByName(both[1])


def s_label_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    like, path = _days(spark, sf_dir)
    stream = lambda: ingest.source(spark, path, like, files=2)
    asks = stream().filter("event_type = 'view'").select(F.col("event_id").alias("request_id"), "user_id", F.col("us").alias("t_us"))
    buys = stream().filter("event_type = 'purchase'").select("user_id", "us")
    found = _through(spark, ingest.label_join(asks, buys, "24 hours", "40 days"))
    return found.filter("label_us is not null").groupBy("request_id").agg(F.count("*").alias("hits"), F.min("label_us").alias("label_us"))


def s_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = _through(spark, state.mutable_state(_stream(spark, sf_dir, True).select("user_id", "us", "event_id"), 2 * DAY), "update")
    last = found.groupBy("user_id").agg(F.max(F.struct("last_us", "n", "first_us")).alias("x"))
    return last.select("user_id", "x.n", "x.first_us", "x.last_us")


_H = f"WITH {sql.HIST} "
QUERIES = {
    "w26_stream_hourly": (w26_stream_hourly, _H + f"SELECT us // {HOUR} AS hour, count(*) AS n FROM H GROUP BY 1"),
    "w27_stream_replay": (w27_stream_replay, f"{sql.base()} {sql.SUMMARY} GROUP BY request_id"),
    "s_tumble": (s_tumble, _H + f"SELECT us // {6 * HOUR} * {6 * HOUR} AS from_us, event_type, count(*) AS n FROM H GROUP BY 1, 2"),
    "s_slide": (s_slide, _H + f"SELECT us // {12 * HOUR} * {12 * HOUR} - k * {12 * HOUR} AS from_us, count(*) AS n FROM H, (VALUES (0), (1)) v(k) GROUP BY 1"),
    "s_session": (s_session, None),
    "s_dedupe": (s_dedupe, "SELECT user_id, count(*) AS n FROM events GROUP BY user_id"),
    "s_late": (s_late, _H + f"SELECT CASE WHEN us >= (SELECT max(us) FROM H) - 10 * {DAY} THEN 'in_time' ELSE 'late' END AS part, count(*) AS n FROM H GROUP BY 1"),
    "s_label_join": (s_label_join, _H + f"SELECT r.event_id AS request_id, count(*) AS hits, min(b.us) AS label_us FROM H r JOIN H b ON b.user_id = r.user_id AND b.event_type = 'purchase' AND b.us > r.us AND b.us <= r.us + {DAY} WHERE r.event_type = 'view' GROUP BY 1"),
    "s_state": (s_state, _H + f", M AS (SELECT user_id, max(us) AS last_us FROM H GROUP BY user_id) SELECT user_id, count(*) AS n, min(us) AS first_us, max(us) AS last_us FROM H JOIN M USING (user_id) WHERE us >= M.last_us - 2 * {DAY} GROUP BY user_id"),
}
