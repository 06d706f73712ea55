"""What the method is compared with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from histreplay.operators.history import sequences, window_events
from histreplay.operators.replay import _tail
from histreplay.schema import DAY, EVENT_COLUMNS


def wide_row(requests: DataFrame, hist: DataFrame, max_len: int | None = None, lookback_days: int = 30, labels: DataFrame | None = None) -> DataFrame:
    """The whole sequence copied into every example, cut to the union's longest length; labels join late, by request."""
    wide = sequences(window_events(requests, hist, lookback_days), ["request_id", "user_id", "t_us"])
    if max_len is not None:
        wide = truncate(wide, max_len)
    return wide if labels is None else wide.join(labels, "request_id", "left")


def truncate(wide: DataFrame, length: int) -> DataFrame:
    """A tenant's cut of the arrays after they have been read in full."""
    return wide.withColumns({t: _tail(F.col(t), F.lit(length)) for t in EVENT_COLUMNS if t in wide.columns})


def union_read(wide_lengths: DataFrame, max_len: int) -> DataFrame:
    """(read_elems): what every tenant reads of a union table of that length."""
    return wide_lengths.agg(F.sum(F.least(F.col("n"), F.lit(max_len))).cast("long").alias("read_elems"))


def snapshot_join(snapshots: DataFrame, labels: DataFrame, horizon: int) -> DataFrame:
    """Features frozen at request time, joined with the first label of the user within the horizon, if any."""
    hit = snapshots.join(labels.select("user_id", F.col("us").alias("label_us")), "user_id").filter((F.col("label_us") > F.col("t_us")) & (F.col("label_us") <= F.col("t_us") + horizon))
    first = hit.groupBy("request_id").agg(F.min("label_us").alias("label_us"))
    return snapshots.join(first, "request_id", "left").withColumn("label", F.col("label_us").isNotNull().cast("int"))


def etl_join(requests: DataFrame, hist: DataFrame, as_of: str = "day_end") -> DataFrame:
    """Event rows of a side-table join at ETL time: state as of the end of the request's day, not of the request."""
    end = (F.floor(F.col("t_us") / DAY) + 1) * DAY
    return requests.join(hist, "user_id").filter(F.col("us") < (end if as_of == "day_end" else F.lit(int(as_of))))


def leaky(requests: DataFrame, hist: DataFrame) -> DataFrame:
    """Event rows of a join with the latest state: no bound at all."""
    return requests.join(hist, "user_id")


def lsm_runs(day_no: int, fanout: int) -> int:
    """Runs in a store after `day_no` daily loads if `fanout` runs of a level are merged into one: the digits' sum."""
    runs = 0
    while day_no:
        runs, day_no = runs + day_no % fanout, day_no // fanout
    return runs


def lsm(hist: DataFrame, fanout: int) -> DataFrame:
    """Each event with run_lo, run_hi (days of the run that holds it after the last load) and merges (times rewritten).

    Day d, counted from 1, is in the run that the leftmost differing digit of d - 1 and the number of days decides.
    """
    days = hist.agg(F.min(F.floor(F.col("us") / DAY)).alias("a"), F.max(F.floor(F.col("us") / DAY)).alias("b")).first()
    n, edges, at, size = int(days["b"] - days["a"] + 1), [], 0, 1
    while size * fanout <= n:
        size *= fanout
    level = 0
    while size >= 1:
        while at + size <= n:
            edges.append((at, at + size, size))
            at += size
        size //= fanout
        level += 1
    runs = F.array(*[F.struct(F.lit(a).alias("lo"), F.lit(b).alias("hi"), F.lit(0 if s == 1 else round(math.log(s, fanout))).alias("merges")) for a, b, s in edges])
    day = F.floor(F.col("us") / DAY) - int(days["a"])
    run = F.get(F.filter(runs, lambda r: (r["lo"] <= day) & (day < r["hi"])), F.lit(0))
    return hist.withColumn("run", run).select("*", F.col("run.lo").alias("run_lo"), F.col("run.hi").alias("run_hi"), F.col("run.merges").alias("merges")).drop("run")


def append_store(hist: DataFrame) -> DataFrame:
    """Events with the day partition that holds them: as many runs as days."""
    return hist.withColumn("run_lo", F.floor(F.col("us") / DAY))


def backfill_days(lookback_days: int) -> int:
    """Daily partitions that an append-only store rewrites for a schema change; regeneration needs one run."""
    return lookback_days


def patch_deletes(wide: DataFrame, items: DataFrame) -> DataFrame:
    """(touched_rows, removed_elems): wide rows that hold an event of a deleted item, and how many such events."""
    gone = items.select(F.col(items.columns[0]).alias("item_id")).distinct()
    rows = wide.select("request_id", F.explode("item_id").alias("item_id")).join(gone, "item_id")
    return rows.agg(F.count_distinct("request_id").alias("touched_rows"), F.count("*").alias("removed_elems"))


def monolith(hist: DataFrame) -> DataFrame:
    """One row for each user with a single array of structs: no stripes, no groups, no columns of one's own."""
    return hist.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct(*EVENT_COLUMNS))).alias("events"))


def day_rank(hist: DataFrame) -> DataFrame:
    """Events with their rank in the user's history."""
    return hist.withColumn("rank", F.row_number().over(Window.partitionBy("user_id").orderBy("us", "event_id")) - 1)
