"""Queries of the operators around the methods, on the given tables."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from histreplay.functions.digest import event_hash
from histreplay.operators import baselines, consumers, generations, history, joins, layers, stripes, tier
from histreplay.queries import sql
from histreplay.queries.methods import LAYOUT, _hist
from histreplay.schema import DAY, EVENT_COLUMNS, HOUR
from histreplay.sources import tables
from histreplay.sources.scratch import folder
from histreplay.sources.tables import micros

Query = Callable[[SparkSession, str], DataFrame]


def _scan(name: str, key: str, total: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return tables.table(spark, sf_dir, name).agg(F.count("*").alias("n"), F.count_distinct(key).alias("keys"), F.round(F.sum(F.col(total).cast("double")), 2).alias("total"))

    return run


_SCANS = {"events": ("user_id", "value"), "orders": ("o_custkey", "o_totalprice"), "lineitem": ("l_orderkey", "l_quantity"), "customer": ("c_nationkey", "c_acctbal"), "part": ("p_brand", "p_retailprice"), "documents": ("lang", "n_chars"), "pages": ("url", "page_id"), "conversations": ("conv_id", "turn"), "labels": ("doc_id", "quality")}


def _of(name: str) -> Callable[[Callable[[DataFrame], DataFrame]], Query]:
    return lambda make: lambda spark, sf_dir: make(tables.table(spark, sf_dir, name))


def o_project(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = stripes.build(_hist(spark, sf_dir), LAYOUT)
    return st.select("user_id", "stripe_no", F.get("event_id", F.lit(0)).alias("first_id"))


def o_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    lo = 1_704_067_200_000_000
    return hist.filter(F.col("us").between(lo + DAY, lo + 8 * DAY) & F.col("feature_group").isin("dense", "sparse")).groupBy("event_type").agg(F.count("*").alias("n"))


def _joined(hint: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        users = tables.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
        return tables.events(spark, sf_dir).join(users.hint(hint), "user_id").groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("value"))

    return run


def o_join_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    users = tables.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return joins.salted(tables.events(spark, sf_dir).select("user_id", "value"), users, "user_id", 8).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("value"))


def o_cross(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tenants with days: a small product by nature."""
    days = tables.events(spark, sf_dir).select(F.floor(F.col("us") / DAY).alias("day")).distinct()
    return days.crossJoin(F.broadcast(spark.createDataFrame([("A", 64), ("B", 16), ("C", 4)], "tenant string, len int")))


def o_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    asks = history.requests_of(_hist(spark, sf_dir)).withColumn("lo_us", F.col("t_us") - 3 * DAY)
    found = joins.in_range(asks, _hist(spark, sf_dir), "user_id", "us", "lo_us", "t_us", DAY)
    return found.groupBy("request_id").agg(F.count("*").alias("n"))


def o_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    buys = hist.filter("event_type = 'purchase'").select("user_id", F.col("us").alias("buy_us"))
    clicks = hist.filter("event_type = 'click'")
    return clicks.join(buys, "user_id").filter((F.col("buy_us") > F.col("us")) & (F.col("buy_us") <= F.col("us") + 6 * HOUR)).groupBy("user_id").agg(F.count("*").alias("n"))


def o_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    buys = hist.filter("event_type = 'purchase'").select("user_id", "us", F.col("event_id").alias("last_buy"))
    return joins.asof(history.requests_of(hist), buys, "user_id", "t_us", "us", "last_buy").select("request_id", F.coalesce("last_buy", F.lit(-1)).alias("last_buy"))


def _membership(how: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        users = tables.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
        return users.join(tables.events(spark, sf_dir).select("user_id").distinct(), "user_id", how).groupBy("c_nationkey").agg(F.count("*").alias("n"))

    return run


def o_outer(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, line = tables.table(spark, sf_dir, "orders"), tables.table(spark, sf_dir, "lineitem")
    per = line.groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.count("*").alias("lines"))
    return o.join(per, "o_orderkey", "full").groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum(F.coalesce("lines", F.lit(0))).alias("lines"))


def o_agg(df: DataFrame) -> DataFrame:
    return df.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), F.round(F.avg("l_discount"), 6).alias("discount"))


def o_collect(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _hist(spark, sf_dir).groupBy("user_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("us", "event_id", "event_type"))), lambda e: F.substring(e["event_type"], 1, 1)), "").alias("kinds"))


def o_distinct(df: DataFrame) -> DataFrame:
    return df.groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct("props").alias("props"))


def o_approx(df: DataFrame) -> DataFrame:
    return df.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", 0.99, 10_000).alias("p99"))


def _grouped(kind: str) -> Callable[[DataFrame], DataFrame]:
    def make(df: DataFrame) -> DataFrame:
        g = df.withColumn("year", F.year("o_orderdate"))
        g = g.cube("o_orderstatus", "year") if kind == "cube" else g.rollup("o_orderstatus", "year")
        return g.agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total")).select(F.coalesce("o_orderstatus", F.lit("*")).alias("status"), F.coalesce("year", F.lit(-1)).alias("year"), "n", "total")

    return make


def o_gsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    tables.table(spark, sf_dir, "orders").createOrReplaceTempView("o_gsets_orders")
    return spark.sql("SELECT coalesce(o_orderstatus, '*') AS status, coalesce(o_orderpriority, '*') AS priority, count(*) AS n FROM o_gsets_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


def o_pivot(df: DataFrame) -> DataFrame:
    return df.groupBy("user_id").pivot("event_type", ["view", "click", "purchase"]).count().select("user_id", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("view", "click", "purchase")])


def o_stat(df: DataFrame) -> DataFrame:
    return df.groupBy("l_returnflag").agg(F.count_if(F.col("l_discount") > 0.05).alias("high"), F.bool_and(F.col("l_quantity") > 0).alias("positive"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"))


def o_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    d = Window.partitionBy("o_custkey").orderBy("o_orderdate")
    return tables.table(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(d).alias("rk"), F.dense_rank().over(d).alias("dr"), F.ntile(4).over(w).alias("quarter"))


def o_lead(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("us", "event_id")
    return _hist(spark, sf_dir).select("event_id", F.coalesce(F.col("us") - F.lag("us").over(w), F.lit(-1)).alias("gap"), F.coalesce(F.lead("event_type").over(w), F.lit("-")).alias("next"), F.first_value("event_id").over(w).alias("first_id"))


def o_frame_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("us", "event_id").rowsBetween(-3, 0)
    return _hist(spark, sf_dir).select("event_id", F.round(F.avg("value").over(w), 6).alias("mean4"))


def o_frame_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-7 * DAY, 0)
    return _hist(spark, sf_dir).select("event_id", F.count("*").over(w).alias("week"))


def o_topk(df: DataFrame) -> DataFrame:
    return df.orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


def o_topk_per_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(F.col("us").desc(), F.col("event_id").desc())
    return _hist(spark, sf_dir).withColumn("rn", F.row_number().over(w)).filter("rn <= 5").select("user_id", "rn", "event_id")


def _set(kind: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        hist = _hist(spark, sf_dir)
        a, b = (hist.filter(F.col("event_type") == k).select("user_id", "item_id") for k in ("view", "click"))
        out = {"union": a.unionByName(b), "union_distinct": a.unionByName(b).distinct(), "intersect": a.intersect(b), "intersect_all": a.intersectAll(b), "except": a.subtract(b), "except_all": a.exceptAll(b)}[kind]
        return out.groupBy("user_id").agg(F.count("*").alias("n"), F.sum("item_id").alias("items"))

    return run


def o_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = stripes.build(_hist(spark, sf_dir), LAYOUT)
    items = F.col("item_id")
    return st.select(
        "user_id", "stripe_no", F.size(F.array_distinct(items)).alias("kinds"), F.array_position(F.array_sort(items), F.get(items, F.lit(0))).alias("place"), F.size(F.filter(items, lambda x: x < 50)).alias("low"),
        F.aggregate(F.slice(items, 2, 3), F.lit(0), lambda a, x: a + x).alias("mid"), F.get(F.concat(items, F.array(F.lit(-1).cast("int"))), F.size(items)).alias("end"), F.size(F.flatten(F.array(items, items))).alias("twice"),
    )


def o_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    st = stripes.build(_hist(spark, sf_dir), LAYOUT)
    m = F.map_from_arrays("event_id", "event_type")
    return st.withColumn("m", m).select("user_id", "stripe_no", F.element_at("m", F.get("event_id", F.lit(0))).alias("first_kind"), F.size(F.map_keys("m")).alias("n"))


def o_json(df: DataFrame) -> DataFrame:
    k = F.from_json("props", "k INT")["k"]
    return df.groupBy(k.alias("k")).agg(F.count("*").alias("n"), F.count_if(F.get_json_object("props", "$.k").cast("int") == k).alias("same"), F.max(F.to_json(F.struct(k.alias("k")))).alias("json"))


def o_string(df: DataFrame) -> DataFrame:
    return df.select("c_custkey", F.upper("c_mktsegment").alias("up"), F.substring("c_name", 1, 4).alias("head"), F.concat_ws("-", F.col("c_custkey").cast("string"), "c_mktsegment").alias("joined"), F.regexp_extract("c_name", r"([0-9]+)", 1).alias("digits"), F.size(F.split("c_mktsegment", "")).alias("letters"))


def o_hash(df: DataFrame) -> DataFrame:
    return df.select("c_custkey", F.md5("c_name").alias("md5"), F.sha2("c_name", 256).alias("sha"))


def o_date(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = tables.table(spark, sf_dir, "orders").withColumn("us", micros("o_orderdate"))
    return o.groupBy(F.year("o_orderdate").alias("year"), F.month("o_orderdate").alias("month")).agg(F.count("*").alias("n"), F.min(F.floor(F.col("us") / DAY)).alias("first_day"), F.count_if(F.dayofweek("o_orderdate") == 1).alias("sundays"))


def o_math(df: DataFrame) -> DataFrame:
    q = F.col("l_quantity").cast("long")
    return df.groupBy("l_linenumber").agg(F.round(F.sum(F.ln(F.col("l_extendedprice"))), 4).alias("logs"), F.sum(F.pmod(q, F.lit(7))).alias("mods"), F.bit_or(q).alias("bits"), F.sum(F.call_function("shiftright", q, F.lit(1))).alias("halves"), F.sum(F.bit_get(q, F.lit(0)).cast("long")).alias("odd"))


def o_cond(df: DataFrame) -> DataFrame:
    return df.select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 1000, "low").otherwise("high").alias("band"), F.col("c_name").try_cast("int").isNull().alias("no_number"), F.coalesce(F.nullif("c_nationkey", F.lit(0)), F.lit(-1)).alias("nation"))


def o_pred(df: DataFrame) -> DataFrame:
    return df.agg(F.count_if(F.col("text").like("%License%")).alias("liked"), F.count_if(F.col("text").rlike("[0-9]{3}")).alias("digits"), F.count_if(F.col("lang").eqNullSafe("en")).alias("english"))


def o_sample(df: DataFrame) -> DataFrame:
    """A tenth of the users, decided by their ids."""
    return df.filter(F.conv(F.substring(F.md5(F.col("user_id").cast("string")), 1, 8), 16, 10).cast("long") % 10 == 0).groupBy("user_id").agg(F.count("*").alias("n"))


def o_sql_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """History tails in SQL, over a view of the stripes."""
    stripes.build(_hist(spark, sf_dir), LAYOUT, ("us", "event_id")).createOrReplaceTempView("history_stripes")
    return spark.sql("SELECT user_id, count(*) AS n, max(e.us) AS last_us FROM history_stripes LATERAL VIEW inline(arrays_zip(us, event_id)) e AS us, event_id WHERE stripe_no >= 3 GROUP BY user_id")


def o_orders_ties(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Day-grained histories with ties: the order's number breaks them."""
    o = tables.table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("user_id"), micros("o_orderdate").alias("us"), F.col("o_orderkey").alias("event_id"), F.lit("all").alias("feature_group"))
    st = stripes.build(o, LAYOUT, ("us", "event_id"))
    return st.groupBy("user_id").agg(F.count("*").alias("stripes"), F.sum("n_events").alias("n"), F.max(F.element_at("event_id", -1)).alias("last_id"))


def o_conversation_tail(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations as histories in logical time: the last four turns."""
    w = Window.partitionBy("conv_id").orderBy(F.col("turn").desc())
    rows = tables.table(spark, sf_dir, "conversations").withColumn("back", F.row_number().over(w)).filter("back <= 4")
    return rows.groupBy("conv_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ",").alias("roles"))


def o_layer_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return layers.plan(_hist(spark, sf_dir), 0.2).select("event_type", F.round("share", 9).alias("share"), "feature_group", "days")


def o_layered_build(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    end = hist.agg(F.max(F.floor(F.col("us") / DAY) * DAY)).first()[0]
    return layers.build(hist, {"dense": 7, "sparse": 30}, end).groupBy("feature_group").agg(F.count("*").alias("n"), F.min("us").alias("first_us"))


def o_monolith_vs_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.monolith(_hist(spark, sf_dir)).select("user_id", F.aggregate("events", F.lit(0).cast("long"), lambda a, e: a + event_hash(e["us"], e["event_id"])).alias("digest"))


def o_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = _hist(spark, sf_dir).groupBy("user_id").agg(F.count("*").alias("n"))
    return n.select("user_id", consumers.pair_count(F.col("n")).alias("full"), consumers.pair_count(F.col("n"), 16).alias("banded"))


def o_topk_category(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = _hist(spark, sf_dir)
    seq = history.sequences(hist.withColumn("request_id", F.col("user_id")), ["request_id"])
    return consumers.topk_by_category(seq, F.lit("purchase"), 3).select("request_id", F.size("top").alias("n"), F.coalesce(F.get(F.col("top")["event_id"], F.lit(0)), F.lit(-1)).alias("latest"))


def o_topk_vector(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = _hist(spark, sf_dir).filter("event_type = 'click'").select(F.col("user_id").alias("request_id"), "item_id")
    return consumers.topk_by_vector(events, tables.table(spark, sf_dir, "embeddings"), [1.0] * 32 + [-1.0] * 32, 3).select("request_id", "item_id", "rank")


def o_sample_length(spark: SparkSession, sf_dir: str) -> DataFrame:
    return history.requests_of(_hist(spark, sf_dir)).select("request_id", consumers.sample_length(F.col("request_id"), 64, 5).alias("length"))


def o_registry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two generations are written and published; a rollback brings the first one back, and a pinned reader keeps the second.

    (generation, events, digest) of what the readers get: the published one after the rollback, and the pinned one.
    """
    hist = _hist(spark, sf_dir)
    end = hist.agg(F.max(F.floor(F.col("us") / DAY) * DAY)).first()[0]
    registry = generations.Registry(spark, f"builds_{uuid.uuid4().hex[:12]}", LAYOUT, f"{folder(spark)}/builds-{uuid.uuid4().hex}")
    codecs = tier.plan(hist, EVENT_COLUMNS)
    for gen in (0, 1):
        registry.write(generations.rebuild(hist, end - (1 - gen) * DAY, 14, LAYOUT), gen, codecs)
        registry.publish(gen)
    current = registry.rollback()
    readers = {current: registry.read(), 1: registry.read(1)}
    sums = [generations.content_digest(g).withColumn("generation", F.lit(k)) for k, g in readers.items()]
    return sums[0].unionByName(sums[1])


_H = f"WITH {sql.HIST} "
_ST = _H.rstrip() + ", ST AS (SELECT *, CAST((row_number() OVER (PARTITION BY user_id ORDER BY us, event_id) - 1) // 8 AS BIGINT) AS stripe_no FROM H) "
_SEG = "SELECT c_mktsegment, count(*) AS n, round(sum(value), 4) AS value FROM events JOIN customer ON c_custkey = user_id GROUP BY c_mktsegment"
_SETS = {"union": "UNION ALL", "union_distinct": "UNION", "intersect": "INTERSECT", "intersect_all": "INTERSECT ALL", "except": "EXCEPT", "except_all": "EXCEPT ALL"}
_GR = "SELECT coalesce(o_orderstatus, '*') AS status, CAST(coalesce(year, -1) AS INTEGER) AS year, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM (SELECT *, year(o_orderdate) AS year FROM orders) GROUP BY {}(o_orderstatus, year)"


def _gen(k: int) -> str:
    end = f"((SELECT max(us // {DAY} * {DAY}) FROM H) - {k} * {DAY})"
    return f"SELECT {1 - k} AS generation, count(*) AS events, CAST(sum({sql.HASH32}) AS BIGINT) AS digest FROM H WHERE us < {end} AND us >= {end} - 14 * {DAY}"


QUERIES = {
    **{f"o_scan_{t}": (_scan(t, k, v), f"SELECT count(*) AS n, count(DISTINCT {k}) AS keys, round(sum(CAST({v} AS DOUBLE)), 2) AS total FROM {t}") for t, (k, v) in _SCANS.items()},
    "o_project": (o_project, _ST + "SELECT user_id, stripe_no, arg_min(event_id, (us, event_id)) AS first_id FROM ST GROUP BY ALL"),
    "o_filter": (o_filter, _H + f"SELECT event_type, count(*) AS n FROM H WHERE us BETWEEN 1704067200000000 + {DAY} AND 1704067200000000 + 8 * {DAY} AND feature_group IN ('dense', 'sparse') GROUP BY event_type"),
    "o_join_smj": (_joined("merge"), _SEG),
    "o_join_shj": (_joined("shuffle_hash"), _SEG),
    "o_join_bhj": (_joined("broadcast"), _SEG),
    "o_join_salted": (o_join_salted, _SEG),
    "o_cross": (o_cross, _H + f"SELECT DISTINCT us // {DAY} AS day, tenant, len FROM H, (VALUES ('A', 64), ('B', 16), ('C', 4)) v(tenant, len)"),
    "o_range": (o_range, _H + f"SELECT r.event_id AS request_id, count(*) AS n FROM H r JOIN H h ON h.user_id = r.user_id AND h.us BETWEEN r.us - 3 * {DAY} AND r.us WHERE r.event_type = 'view' GROUP BY 1"),
    "o_interval": (o_interval, _H + f"SELECT c.user_id, count(*) AS n FROM H c JOIN H b ON b.user_id = c.user_id AND b.event_type = 'purchase' AND b.us > c.us AND b.us <= c.us + 6 * {HOUR} WHERE c.event_type = 'click' GROUP BY 1"),
    "o_asof": (o_asof, _H + "SELECT r.event_id AS request_id, coalesce(b.event_id, -1) AS last_buy FROM (SELECT * FROM H WHERE event_type = 'view') r ASOF LEFT JOIN (SELECT * FROM H WHERE event_type = 'purchase') b ON b.user_id = r.user_id AND b.us <= r.us"),
    "o_semi": (_membership("left_semi"), "SELECT c_nationkey, count(*) AS n FROM customer WHERE c_custkey IN (SELECT user_id FROM events) GROUP BY 1"),
    "o_anti": (_membership("left_anti"), "SELECT c_nationkey, count(*) AS n FROM customer WHERE c_custkey NOT IN (SELECT user_id FROM events) GROUP BY 1"),
    "o_outer": (o_outer, "SELECT o_orderstatus, count(*) AS n, CAST(sum(coalesce(lines, 0)) AS BIGINT) AS lines FROM orders FULL JOIN (SELECT l_orderkey, count(*) AS lines FROM lineitem GROUP BY 1) ON l_orderkey = o_orderkey GROUP BY 1"),
    "o_agg": (_of("lineitem")(o_agg), "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS discount FROM lineitem GROUP BY 1, 2"),
    "o_collect": (o_collect, _H + "SELECT user_id, string_agg(substr(event_type, 1, 1), '' ORDER BY us, event_id) AS kinds FROM H GROUP BY user_id"),
    "o_distinct": (_of("events")(o_distinct), "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT props) AS props FROM events GROUP BY 1"),
    "o_approx": (_of("events")(o_approx), None),
    "o_cube": (_of("orders")(_grouped("cube")), _GR.format("CUBE ")),
    "o_rollup": (_of("orders")(_grouped("rollup")), _GR.format("ROLLUP ")),
    "o_gsets": (o_gsets, "SELECT coalesce(o_orderstatus, '*') AS status, coalesce(o_orderpriority, '*') AS priority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"),
    "o_pivot": (_of("events")(o_pivot), "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS {k}" for k in ("view", "click", "purchase")) + " FROM events GROUP BY user_id"),
    "o_stat": (_of("lineitem")(o_stat), "SELECT l_returnflag, count(*) FILTER (l_discount > 0.05) AS high, bool_and(l_quantity > 0) AS positive, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS corr FROM lineitem GROUP BY 1"),
    "o_rank": (o_rank, "SELECT o_orderkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER d AS INTEGER) AS rk, CAST(dense_rank() OVER d AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS quarter FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), d AS (PARTITION BY o_custkey ORDER BY o_orderdate)"),
    "o_lead": (o_lead, _H + "SELECT event_id, coalesce(us - lag(us) OVER w, -1) AS gap, coalesce(lead(event_type) OVER w, '-') AS next, first_value(event_id) OVER w AS first_id FROM H WINDOW w AS (PARTITION BY user_id ORDER BY us, event_id)"),
    "o_frame_rows": (o_frame_rows, _H + "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY us, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 6) AS mean4 FROM H"),
    "o_frame_range": (o_frame_range, _H + f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY us RANGE BETWEEN {7 * DAY} PRECEDING AND CURRENT ROW) AS week FROM H"),
    "o_topk": (_of("orders")(o_topk), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20"),
    "o_topk_per_key": (o_topk_per_key, _H + "SELECT user_id, CAST(rn AS INTEGER) AS rn, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY us DESC, event_id DESC) AS rn FROM H) WHERE rn <= 5"),
    **{f"o_set_{k}": (_set(k), _H + f"SELECT user_id, count(*) AS n, CAST(sum(item_id) AS BIGINT) AS items FROM (SELECT user_id, item_id FROM H WHERE event_type = 'view' {op} SELECT user_id, item_id FROM H WHERE event_type = 'click') GROUP BY user_id") for k, op in _SETS.items()},
    "o_array": (o_array, _ST + ", A AS (SELECT user_id, stripe_no, list(item_id ORDER BY us, event_id) AS x FROM ST GROUP BY ALL) SELECT user_id, stripe_no, CAST(len(list_distinct(x)) AS INTEGER) AS kinds, list_position(list_sort(x), x[1]) AS place, CAST(len(list_filter(x, lambda e: e < 50)) AS INTEGER) AS low, CAST(coalesce(list_sum(x[2:4]), 0) AS INTEGER) AS mid, -1 AS end, CAST(2 * len(x) AS INTEGER) AS twice FROM A"),
    "o_map": (o_map, _ST + "SELECT user_id, stripe_no, arg_min(event_type, (us, event_id)) AS first_kind, CAST(count(*) AS INTEGER) AS n FROM ST GROUP BY ALL"),
    "o_json": (_of("events")(o_json), _H + "SELECT item_id AS k, count(*) AS n, count(*) AS same, '{\"k\":' || item_id || '}' AS json FROM H GROUP BY item_id"),
    "o_string": (_of("customer")(o_string), "SELECT c_custkey, upper(c_mktsegment) AS up, substr(c_name, 1, 4) AS head, c_custkey || '-' || c_mktsegment AS joined, regexp_extract(c_name, '([0-9]+)', 1) AS digits, CAST(length(c_mktsegment) AS INTEGER) AS letters FROM customer"),
    "o_hash": (_of("customer")(o_hash), "SELECT c_custkey, md5(c_name) AS md5, sha256(c_name) AS sha FROM customer"),
    "o_date": (o_date, f"SELECT CAST(year(o_orderdate) AS INTEGER) AS year, CAST(month(o_orderdate) AS INTEGER) AS month, count(*) AS n, min(epoch_us(o_orderdate) // {DAY}) AS first_day, count(*) FILTER (dayofweek(o_orderdate) = 0) AS sundays FROM orders GROUP BY 1, 2"),
    "o_math": (_of("lineitem")(o_math), "SELECT l_linenumber, round(sum(ln(l_extendedprice)), 4) AS logs, CAST(sum(CAST(l_quantity AS BIGINT) % 7) AS BIGINT) AS mods, bit_or(CAST(l_quantity AS BIGINT)) AS bits, CAST(sum(CAST(l_quantity AS BIGINT) >> 1) AS BIGINT) AS halves, CAST(sum(CAST(l_quantity AS BIGINT) & 1) AS BIGINT) AS odd FROM lineitem GROUP BY 1"),
    "o_cond": (_of("customer")(o_cond), "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 1000 THEN 'low' ELSE 'high' END AS band, TRY_CAST(c_name AS INTEGER) IS NULL AS no_number, coalesce(nullif(c_nationkey, 0), -1) AS nation FROM customer"),
    "o_pred": (_of("documents")(o_pred), "SELECT count(*) FILTER (text LIKE '%License%') AS liked, count(*) FILTER (regexp_matches(text, '[0-9]{3}')) AS digits, count(*) FILTER (lang IS NOT DISTINCT FROM 'en') AS english FROM documents"),
    "o_sample": (_of("events")(o_sample), "SELECT user_id, count(*) AS n FROM events WHERE CAST('0x' || substr(md5(CAST(user_id AS VARCHAR)), 1, 8) AS BIGINT) % 10 = 0 GROUP BY user_id"),
    "o_sql_view": (o_sql_view, _ST + "SELECT user_id, count(*) AS n, max(us) AS last_us FROM ST WHERE stripe_no >= 3 GROUP BY user_id"),
    "o_orders_ties": (o_orders_ties, "WITH N AS (SELECT o_custkey AS user_id, o_orderkey, (row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) - 1) // 8 AS s, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS rn, count(*) OVER (PARTITION BY o_custkey) AS c FROM orders) SELECT user_id, count(DISTINCT s) AS stripes, count(*) AS n, max(o_orderkey) FILTER (rn % 8 = 0 OR rn = c) AS last_id FROM N GROUP BY user_id"),
    "o_conversation_tail": (o_conversation_tail, "SELECT conv_id, string_agg(role, ',' ORDER BY turn) AS roles FROM (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC) AS back FROM conversations) WHERE back <= 4 GROUP BY conv_id"),
    "o_layer_plan": (o_layer_plan, "SELECT event_type, round(count(*) / (SELECT count(*) FROM events), 9) AS share, CASE WHEN count(*) / (SELECT count(*) FROM events) >= 0.2 THEN 'dense' ELSE 'sparse' END AS feature_group, CASE WHEN count(*) / (SELECT count(*) FROM events) >= 0.2 THEN 7 ELSE 30 END AS days FROM events GROUP BY event_type"),
    "o_layered_build": (o_layered_build, _H + f", E AS (SELECT max(us // {DAY} * {DAY}) AS e FROM H) SELECT feature_group, count(*) AS n, min(us) AS first_us FROM H, E WHERE us < e AND us >= e - CASE feature_group WHEN 'dense' THEN 7 WHEN 'sparse' THEN 30 END * {DAY} GROUP BY feature_group"),
    "o_monolith_vs_columns": (o_monolith_vs_columns, _H + f"SELECT user_id, CAST(sum({sql.HASH32}) AS BIGINT) AS digest FROM H GROUP BY user_id"),
    "o_pairs": (o_pairs, "SELECT user_id, count(*) * (count(*) + 1) // 2 AS full, CASE WHEN count(*) <= 16 THEN count(*) * (count(*) + 1) // 2 ELSE 136 + (count(*) - 16) * 16 END AS banded FROM events GROUP BY user_id"),
    "o_topk_category": (o_topk_category, _H + "SELECT user_id AS request_id, CAST(least(3, count(*) FILTER (event_type = 'purchase')) AS INTEGER) AS n, coalesce(max(event_id) FILTER (event_type = 'purchase'), -1) AS latest FROM H GROUP BY user_id"),
    "o_topk_vector": (o_topk_vector, _H + ", S AS (SELECT vec_id, list_sum(list_transform(embedding, lambda x, i: CAST(x AS DOUBLE) * CASE WHEN i <= 32 THEN 1 ELSE -1 END)) AS s FROM embeddings), C AS (SELECT DISTINCT user_id, item_id, s FROM H JOIN S ON vec_id = item_id WHERE event_type = 'click') SELECT user_id AS request_id, item_id, CAST(rank AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY s DESC, item_id) AS rank FROM C) WHERE rank <= 3"),
    "o_sample_length": (o_sample_length, _H + "SELECT event_id AS request_id, CAST(CAST('0x' || substr(md5(event_id || ':5'), 1, 8) AS BIGINT) % 64 + 1 AS INTEGER) AS length FROM H WHERE event_type = 'view'"),
    "o_registry": (o_registry, f"{_H} {_gen(1)} UNION ALL {_gen(0)}"),
}
