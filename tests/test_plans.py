"""Plans: what is read, and what is not shuffled."""

import re

import pytest
from pyspark.sql import functions as F

from histreplay import session
from histreplay.operators import affinity, generations, history, joins, protocol, replay, stripes
from histreplay.plans import prep
from histreplay.queries import methods
from histreplay.schema import LayoutSpec, TenantSpec
from histreplay.sources import files, tables
from histreplay.sources.connector import StripeSource

SF = "/root/testdata/sf0.001"


def hist_of(spark):
    return history.canonical(tables.events(spark, SF))


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_co_sharded_join_has_no_exchange(spark):
    former = session.tune(spark)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        hist = hist_of(spark)
        st = stripes.build(hist, LayoutSpec(stripe_len=8), ("us", "event_id"))
        probe = stripes.index(st).select("user_id", "feature_group", "stripe_no")
        a, b = affinity.co_shard(probe, st, 4, ("probe_sym", "build_sym"))
        assert "Exchange" not in plan(replay.index_join(a, b))
        a, b = affinity.co_shard(probe, st, 4, ("probe_asym", "build_asym"), symmetric=False)
        assert "Exchange" in plan(replay.index_join(a, b))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        session.restore(spark, former)


def test_trait_and_stripe_pushdown(spark, tmp_path):
    st = stripes.build(hist_of(spark), LayoutSpec(stripe_len=8))
    st.write.parquet(str(tmp_path / "st"))
    read = spark.read.parquet(str(tmp_path / "st")).filter("stripe_no >= 2 and last_us > 5").select("user_id", "us")
    text = plan(read)
    assert re.search(r"PushedFilters: \[.*GreaterThanOrEqual\(stripe_no,2\)", text)
    assert "event_type" not in re.search(r"ReadSchema: (.*)", text)[1]


def test_pointer_plan_reads_no_sequence(spark):
    hist = hist_of(spark)
    text = plan(protocol.pointers(history.requests_of(hist), hist))
    assert "collect_list" not in text and "Join" not in text


def test_registry(spark):
    hist = hist_of(spark)
    end = hist.agg({"us": "max"}).first()[0]
    reg = generations.Registry(spark, "hist_test", LayoutSpec(stripe_len=8, buckets=4))
    for gen in (1, 2, 3):
        reg.write(generations.rebuild(hist, end - (3 - gen) * 86_400_000_000, 14), gen)
        reg.publish(gen)
    pinned = reg.read(1).count()
    assert reg.rollback() == 2
    reg.publish(3)
    assert reg.vacuum(2) == [1] and pinned > 0
    assert spark.table("hist_test").count() == reg.read(3).count()


def test_rollback_needs_an_earlier_publication(spark):
    reg = generations.Registry(spark, "hist_once", LayoutSpec(stripe_len=8, buckets=4))
    reg.write(stripes.build(hist_of(spark), LayoutSpec(stripe_len=8)), 7)
    reg.publish(7)
    with pytest.raises(ValueError):
        reg.rollback()
    assert generations.Registry(spark, "hist_once").published == [7]


def test_stored_tier_reads_wanted_columns_and_is_not_shuffled(spark):
    """Encoded columns of unwanted traits stay in the files; a join by stripe meets the tier's buckets as they are."""
    former = session.tune(spark)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        registry, slim = methods.stored(spark, SF)
        table = spark.table(registry.table(1))
        assert {"us_delta", "event_id_delta", "event_type_words", "event_type_codes", "value"} <= set(table.columns)
        read = registry.read(1, ("us",)).filter("user_id = 3 and stripe_no >= 2")
        text, columns = plan(read), read._jdf.queryExecution().executedPlan().collectLeaves().apply(0).output().mkString(",")
        assert "us_delta" in columns and "event_type" not in columns and "value" not in columns
        assert "EqualTo(user_id,3)" in text and "GreaterThanOrEqual(stripe_no,2)" in text
        asks = slim.select("request_id", "user_id", F.inline("pointers")).select("request_id", "user_id", "feature_group", F.lit(0).cast("long").alias("stripe_no"))
        assert "Exchange" not in plan(replay.index_join(asks, registry.read(1, ("us",))))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        session.restore(spark, former)


def test_stored_tier_holds_the_stripes(spark):
    registry, _ = methods.stored(spark, SF)
    want = stripes.build(hist_of(spark), methods.LAYOUT)
    assert want.exceptAll(registry.read(1).select(*want.columns)).count() == 0


def test_intervals_meet_once(spark):
    rows = [(k, k % 3, 7 * k % 90, 7 * k % 90 + k % 40) for k in range(120)]
    a, b = (spark.createDataFrame(rows, f"{x} long, key long, {x}_lo long, {x}_hi long") for x in "ab")
    found = joins.overlapping(a, b, ["key"], ("a_lo", "a_hi"), ("b_lo", "b_hi"), 16).collect()
    got = {(r["a"], r["b"]) for r in found}
    assert len(got) == len(found) and got == {(x[0], y[0]) for x in rows for y in rows if x[1] == y[1] and x[2] <= y[3] and x[3] >= y[2]}


def test_connector_and_files(spark, tmp_path):
    st = stripes.index(stripes.build(hist_of(spark), LayoutSpec(stripe_len=8)))
    path = str(tmp_path / "st")
    st.write.parquet(path)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(StripeSource)
    got = spark.read.format("stripes").option("path", path).load()
    assert got.count() == st.count()
    assert got.filter("user_id >= 3 and user_id <= 5").count() == st.filter("user_id between 3 and 5").count()
    for kind in files.FORMATS:
        files.write(st, str(tmp_path / kind), kind)
        assert files.read(spark, str(tmp_path / kind), st.schema, kind).exceptAll(st).count() == 0


def test_prep_jobs(spark):
    hist = hist_of(spark)
    slim, st = protocol.snapshot(history.requests_of(hist), hist), stripes.build(hist, LayoutSpec(stripe_len=8))
    jobs = [prep.JobSpec(TenantSpec("C", 4, traits=("event_type",))), prep.JobSpec(TenantSpec("A", 64))]
    short, full = prep.run_many(jobs, slim, st)
    tails = {r["request_id"]: r["event_id"] for r in full.collect()}
    assert all(r["event_id"] == tails[r["request_id"]][-4:] for r in short.collect())
    assert prep.prepared(short, 16).count() == len(tails)
    assert sum(b.num_rows for b in prep.batches(short.select("request_id"))) == len(tails)


@pytest.mark.parametrize("most", [12, 4])
def test_many_stripes_are_broadcast_in_rounds(spark, monkeypatch, most):
    """More stripes than are sent at once: the same rows, also where one history alone has more (most 4)."""
    hist = hist_of(spark).filter("user_id < 3")
    slim, st = protocol.snapshot(history.requests_of(hist), hist).persist(), stripes.build(hist, LayoutSpec(stripe_len=8)).persist()
    assert st.count() > 12 and st.groupBy("user_id").count().filter("count > 4").count()
    want = sorted(replay.reconstruct(slim, st, 16, "range").collect())
    monkeypatch.setattr(replay, "BROADCAST_STRIPES", most)
    assert want and sorted(replay.reconstruct(slim, st, 16, "broadcast").collect()) == want
