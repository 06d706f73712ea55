"""Canonical histories, requests, labels, and the state of a history at a time."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from histreplay.functions.digest import ordered
from histreplay.schema import DAY, EVENT_COLUMNS, GROUPS


def group_of(event_type: Column, groups: dict[str, str] = GROUPS) -> Column:
    return F.coalesce(F.create_map(*[F.lit(x) for pair in groups.items() for x in pair])[event_type], F.lit("ops"))


def canonical(events: DataFrame, key: str = "user_id", groups: dict[str, str] = GROUPS) -> DataFrame:
    """One copy of all events: (user_id, us, event_id, event_type, value, item_id, feature_group)."""
    item = F.get_json_object("props", "$.k").cast("int")
    return events.select(F.col(key).alias("user_id"), "us", "event_id", "event_type", "value", item.alias("item_id"), group_of(F.col("event_type"), groups).alias("feature_group"))


def no_future(df: DataFrame, t_col: str = "t_us") -> DataFrame:
    return df.filter(F.col("us") <= F.col(t_col))


def requests_of(hist: DataFrame, kind: str = "view") -> DataFrame:
    """Every event of a kind is a ranking request: (request_id, user_id, t_us)."""
    return hist.filter(F.col("event_type") == kind).select(F.col("event_id").alias("request_id"), "user_id", F.col("us").alias("t_us"))


def k_grid(hist: DataFrame, ks: tuple[int, ...]) -> DataFrame:
    """(k, user_id, t_us): k evenly spaced requests on each day that a user has events, for each k."""
    days = hist.select("user_id", F.floor(F.col("us") / DAY).alias("day")).distinct()
    k = F.explode(F.array(*[F.lit(x) for x in ks])).alias("k")
    grid = days.select("user_id", "day", k).select("user_id", "day", "k", F.explode(F.sequence(F.lit(1), F.col("k"))).alias("j"))
    return grid.select("k", "user_id", (F.col("day") * DAY + F.floor(F.col("j") * DAY / (F.col("k") + 1))).cast("long").alias("t_us"))


def label(requests: DataFrame, hist: DataFrame, horizon: int = DAY, kind: str = "purchase") -> DataFrame:
    """Adds label (1 if the user has such an event in (t, t + horizon]) and label_us, the first one's time."""
    good = hist.filter(F.col("event_type") == kind).select("user_id", F.col("us").alias("label_us"))
    hit = requests.join(good, "user_id").filter((F.col("label_us") > F.col("t_us")) & (F.col("label_us") <= F.col("t_us") + horizon))
    first = hit.groupBy("request_id").agg(F.min("label_us").alias("label_us"))
    return requests.join(first, "request_id", "left").withColumn("label", F.col("label_us").isNotNull().cast("int"))


def window_events(requests: DataFrame, hist: DataFrame, lookback_days: int = 30, cadence: int = DAY, lag: int = 0) -> DataFrame:
    """The events of each request's window, a row each: the reference by which everything else is judged."""
    cutoff = F.floor((F.col("t_us") - lag) / cadence) * cadence
    bounded = requests.withColumns({"cutoff_us": cutoff.cast("long"), "lo_us": (cutoff - (lookback_days - 1) * cadence).cast("long")})
    return bounded.join(hist, "user_id").filter((F.col("us") <= F.col("t_us")) & (F.col("us") >= F.col("lo_us")))


def sequences(rows: DataFrame, keys: list[str], traits: tuple[str, ...] = EVENT_COLUMNS) -> DataFrame:
    """Collects event rows into parallel arrays in (us, event_id) order."""
    rest = [t for t in traits if t not in ("us", "event_id")]
    packed = F.sort_array(F.collect_list(F.struct("us", "event_id", *rest)))
    return rows.groupBy(*keys).agg(packed.alias("ev")).select(*keys, *[F.col("ev")[t].alias(t) for t in traits])


def state_at(hist: DataFrame, requests: DataFrame, lookback_days: int = 30) -> DataFrame:
    """Each request's whole sequence as parallel arrays, by definition: a range join and an ordered collect."""
    return sequences(window_events(requests, hist, lookback_days), ["request_id", "user_id", "t_us"])


def summary(seq: DataFrame) -> DataFrame:
    """(request_id, n, first_us, last_us, digest) of sequences in arrays."""
    return seq.select("request_id", F.size("us").cast("long").alias("n"), F.get("us", F.lit(0)).alias("first_us"), F.get(F.col("us"), F.size("us") - 1).alias("last_us"), ordered(F.col("us"), F.col("event_id")).alias("digest"))


def check_append_only(old: DataFrame, new: DataFrame, cutoff_us: int) -> DataFrame:
    """Rows of the closed range that differ between two snapshots: empty if histories are append-only."""
    before, after = (x.filter(F.col("us") < cutoff_us) for x in (old, new))
    return before.exceptAll(after).withColumn("side", F.lit("gone")).unionByName(after.exceptAll(before).withColumn("side", F.lit("new")))
