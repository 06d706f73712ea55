"""The hand-made case: seven events of one user, cadence 100, stripes of two."""

import pytest
from pyspark.sql import functions as F

from histreplay import sqlapi
from histreplay.functions.digest import ordered
from histreplay.operators import baselines, generations, history, mutable, project, protocol, replay, stripes, verify
from histreplay.schema import LayoutSpec, PointerSpec

EVENTS = [(10, 1, "view"), (40, 2, "click"), (40, 3, "purchase"), (99, 4, "view"), (100, 5, "click"), (150, 6, "view"), (210, 7, "purchase")]
SPEC = PointerSpec(cadence=100, lookback_days=30, digest="ordered")
LAYOUT = LayoutSpec(stripe_len=2)


@pytest.fixture(scope="module")
def hist(spark):
    rows = [(1, us, i, kind, float(i), i, "all") for us, i, kind in EVENTS]
    return spark.createDataFrame(rows, "user_id long, us long, event_id long, event_type string, value double, item_id int, feature_group string")


def request(spark, t, i=6):
    return spark.createDataFrame([(i, 1, t)], "request_id long, user_id long, t_us long")


def slim_of(spark, hist, t, i=6):
    return protocol.snapshot(request(spark, t, i), hist, SPEC)


def test_pointer_and_mutable_part(spark, hist):
    row = slim_of(spark, hist, 150).first()
    assert row["m_event_id"] == [5, 6]
    (p,) = row["pointers"]
    assert (p["start_us"], p["end_us"], p["seq_len"]) == (10, 99, 4)
    assert p["digest"] == "9f204ac33131f0214fee8b56b1b055d3"


def test_stripes(hist):
    rows = {r["stripe_no"]: r for r in stripes.build(hist.filter("us < 100"), LAYOUT).collect()}
    assert rows[0]["event_id"] == [1, 2] and rows[0]["first_us"] == 10 and rows[0]["events_before"] == 0
    assert rows[1]["event_id"] == [3, 4] and rows[1]["first_us"] == 40 and rows[1]["events_before"] == 2


@pytest.mark.parametrize(
    ("length", "ids", "digest"),
    [(None, [1, 2, 3, 4, 5, 6], "41116cd21214918b3c6d73b61e66f3b0"), (3, [4, 5, 6], "f77da712d3071980339dcbd04154ad12"), (5, [2, 3, 4, 5, 6], "4bb2de6f5d27534f8fbe9c0492422622"), (4, [3, 4, 5, 6], None), (2, [5, 6], None), (0, [], None), (50, [1, 2, 3, 4, 5, 6], None)],
)
@pytest.mark.parametrize("strategy", replay.STRATEGIES)
def test_replay(spark, hist, length, ids, digest, strategy):
    st = stripes.build(hist.filter("us < 200"), LAYOUT)
    out = replay.reconstruct(slim_of(spark, hist, 150), st, length, strategy, 2)
    row = out.withColumn("digest", ordered(F.col("us"), F.col("event_id"))).first()
    assert row["event_id"] == ids
    assert digest is None or row["digest"] == digest


def test_spans(spark, hist):
    st = stripes.build(hist.filter("us < 100"), LAYOUT)
    asks = replay.unpack(slim_of(spark, hist, 150))
    got = {n: project.spans(asks, st, n, 2).select("need", "lo", "hi").first() for n in (2, 3, 5)}
    assert tuple(got[3]) == (1, 1, 1) and tuple(got[5]) == (3, 0, 1)
    assert got[2]["need"] == 0 and got[2]["lo"] is None


def test_label_and_leak(spark, hist):
    row = history.label(request(spark, 150), hist, 100).first()
    assert (row["label"], row["label_us"]) == (1, 210)
    assert history.label(request(spark, 150), hist, 50).first()["label"] == 0
    assert verify.leakage(baselines.leaky(request(spark, 150), hist)).first()["leaked_events"] == 1


@pytest.mark.parametrize(("t", "old", "new"), [(100, [1, 2, 3, 4], [5]), (99, [], [1, 2, 3, 4]), (5, [], [])])
def test_cutoff_edges(spark, hist, t, old, new):
    slim = slim_of(spark, hist, t)
    row = slim.first()
    assert row["m_event_id"] == new
    assert sum(p["seq_len"] for p in row["pointers"]) == len(old)
    assert replay.reconstruct(slim, stripes.build(hist, LAYOUT), None, "range").first()["event_id"] == old + new


def test_statuses(spark, hist):
    slim = protocol.snapshot(request(spark, 150), hist, PointerSpec(cadence=100))
    asks = replay.unpack(slim).withColumn("need", F.col("seq_len"))

    def status(source, **kw):
        read = replay.multi_range(asks, project.traits(stripes.build(source, LAYOUT), ("us", "event_id")), "range")
        old = replay.cut(asks, read, ("us", "event_id")).withColumnsRenamed({"i_us": "us", "i_event_id": "event_id"})
        return verify.check(old.join(slim.select("request_id", "user_id"), "request_id"), asks, **kw).first()["status"]

    assert status(hist) == "ok"
    assert status(hist.filter("event_id <> 2")) == "length_mismatch"
    assert status(hist.filter("event_id <> 2"), tombstones=spark.createDataFrame([(1,)], "user_id long")) == "scrubbed"
    assert status(hist.withColumn("event_id", F.when(F.col("event_id") == 2, 9).otherwise(F.col("event_id")))) == "digest_mismatch"
    assert status(hist, projected=True) == "unverifiable_projected"


def test_retention(hist):
    assert [r["event_id"] for r in protocol.retention_gaps(hist, 149, 50, 0).orderBy("event_id").collect()] == [1, 2, 3]
    assert protocol.check_retention(100, 100)
    with pytest.raises(ValueError):
        protocol.check_retention(50, 100)


def test_advance_equals_rebuild(hist):
    day = 86_400_000_000
    spread = hist.withColumn("us", F.col("us") * day / 100).withColumn("us", F.col("us").cast("long"))
    full = generations.rebuild(spread, 2 * day, 1, LAYOUT)
    moved = generations.advance(generations.rebuild(spread, day, 1, LAYOUT), spread.filter((F.col("us") >= day) & (F.col("us") < 2 * day)), 2 * day, 1, LAYOUT)
    assert generations.content_digest(full).first() == generations.content_digest(moved).first()


def test_mutable_tier(hist):
    parts = mutable.fragments(hist.unionByName(hist), 50)
    for p in (parts, mutable.compact(parts)):
        assert mutable.resolve(p, 160, 70).first()["event_id"] == [4, 5, 6]


def test_scrub_logged(spark, hist):
    items = spark.createDataFrame([(5,)], "item_id int")
    assert replay.scrub_logged(slim_of(spark, hist, 150), items).first()["m_event_id"] == [6]


def test_append_only(hist):
    assert history.check_append_only(hist, hist, 200).count() == 0
    assert history.check_append_only(hist, hist.withColumn("value", F.lit(0.0)), 200).count() == 12


def test_empty_history(spark, hist):
    none = hist.limit(0)
    assert stripes.build(none, LAYOUT).count() == 0
    assert replay.reconstruct(slim_of(spark, none, 150), stripes.build(none, LAYOUT), 4, "equi").first()["event_id"] == []


def test_late_event_is_excluded_by_generation(spark, hist):
    first = hist.withColumn("ingest_gen", F.lit(1))
    late = spark.createDataFrame([(1, 20, 8, "view", 0.0, 0, "all", 2)], "user_id long, us long, event_id long, event_type string, value double, item_id int, feature_group string, ingest_gen int")
    st = stripes.build(first.unionByName(late), LAYOUT, ("us", "event_id", "ingest_gen"))
    slim = slim_of(spark, hist, 150)
    assert replay.reconstruct(slim, st, None, "range", generation=1).first()["event_id"] == [1, 2, 3, 4, 5, 6]
    assert replay.reconstruct(slim, st, 3, "range", generation=1).first()["event_id"] == [4, 5, 6]
    assert replay.reconstruct(slim, st, None, "range", generation=2).first()["event_id"] != [1, 2, 3, 4, 5, 6]
    with pytest.raises(ValueError):
        replay.reconstruct(slim, st, None, "equi", generation=1)


def test_history_tail_in_sql(spark, hist):
    sqlapi.register(spark, stripes.build(hist, LAYOUT), "micro")
    rows = spark.sql("SELECT event_id FROM micro_tail(1, 150, 3) ORDER BY us, event_id").collect()
    assert [r["event_id"] for r in rows] == [4, 5, 6]
    got = spark.sql("SELECT r.id, t.event_id FROM VALUES (1, 100L), (2, 45L) r(id, at), LATERAL micro_tail(1, r.at, 2) t ORDER BY 1, 2").collect()
    assert [tuple(r) for r in got] == [(1, 4), (1, 5), (2, 2), (2, 3)]
    assert [r["event_id"] for r in spark.sql("SELECT event_id FROM replay_tail(array(10L, 40L, 99L), array(1L, 2L, 4L), 50L, 1)").collect()] == [2]
