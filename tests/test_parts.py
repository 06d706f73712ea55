import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from histreplay.functions import codec, quality
from histreplay.operators import baselines, batching, joins
from histreplay.plans import autoscale, cost, prefetch


def one(spark, values, kind):
    return spark.createDataFrame([(values,)], f"x array<{kind}>")


@pytest.mark.parametrize("values", [[100, 105, 107, 120], [], [7], [5, 5, 5]])
def test_delta(spark, values):
    row = one(spark, values, "bigint").select(codec.delta_encode(F.col("x")).alias("c")).withColumn("d", codec.delta_decode(F.col("c"))).first()
    assert row["d"] == values
    if len(values) == 4:
        assert row["c"] == [100, 5, 2, 13]


@pytest.mark.parametrize("flags", [[True, False, False, True], [], [True], [True] * 64, [False] * 64, [k % 3 == 0 for k in range(65)], [True] * 130])
def test_bitmap(spark, flags):
    row = one(spark, flags, "boolean").select(codec.bitmap_encode(F.col("x")).alias("c"), F.size("x").alias("n")).withColumn("d", codec.bitmap_decode(F.col("c"), F.col("n"))).first()
    assert row["d"] == flags and len(row["c"]) == -(-len(flags) // 64)
    if len(flags) == 4:
        assert row["c"] == [9]


@pytest.mark.parametrize(("values", "codes"), [(["a", "b", "a", "c"], [0, 1, 0, 2]), ([], []), (["z"], [0])])
def test_dictionary(spark, values, codes):
    df = one(spark, values, "string")
    w, c = codec.dict_encode(F.col("x"))
    row = df.select(w.alias("w"), c.alias("c")).withColumn("d", codec.dict_decode(F.col("w"), F.col("c"))).first()
    assert row["c"] == codes and row["d"] == values


def test_codec_plan():
    got = codec.plan({"like": {"type": "boolean"}, "us": {"type": "long", "ordered": True}, "kind": {"type": "string", "distinct": 5, "rows": 100}, "id": {"type": "string", "distinct": 90, "rows": 100}})
    assert got == {"like": "bitmap", "us": "delta", "kind": "dictionary", "id": "plain"}


def test_rebatch_is_a_permutation(spark):
    rows = spark.range(1000).withColumnRenamed("id", "request_id")
    full = batching.rebatch(batching.base(rows, 64, "request_id"), 300, 1, "request_id").collect()
    assert sorted(r["request_id"] for r in full) == list(range(1000))
    sizes = [sum(r["full_id"] == k for r in full) for k in range(4)]
    assert sizes == [300, 300, 300, 100]


def test_autoscale(spark):
    policy = autoscale.Policy()
    loads = {"view": [4, 1, 0, 9, 1, 1], "click": [0, 0, 3, 3, 0, 0]}
    rows = spark.createDataFrame([(kind, 10 * (7 + t) + k) for kind, own in loads.items() for t, n in enumerate(own) for k in range(n)], "event_type string, us long")
    signals = autoscale.signals(rows, 10)
    series = {(r["job"], r["tick"]): (r["starvation"], r["waste"]) for r in signals.collect()}
    got = {(r["job"], r["tick"]): r["workers"] for r in autoscale.simulate(signals, 10).collect()}
    assert set(got) == set(series) == {(kind, t) for kind in loads for t in range(6)}
    for kind, own in loads.items():
        w, mean = 10, sum(own) / 6
        for t, n in enumerate(own):
            assert series[kind, t] == pytest.approx((max(0, n - mean) / max(n, 1), max(0, mean - n) / mean))
            w = autoscale.step(w, *series[kind, t], policy)
            assert got[kind, t] == w


def test_autoscale_reads_the_events(spark):
    from histreplay.queries import workloads

    files = workloads.w24_autoscale(spark, "/root/testdata/sf0.001").inputFiles()
    assert files and all(f.endswith("events.parquet") for f in files)


@settings(max_examples=10, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 9), st.integers(0, 9)), min_size=1, max_size=8))
def test_makespan(spark, costs):
    df = spark.createDataFrame([(0, k, r, c) for k, (r, c) in enumerate(costs)], "worker int, batch_id int, read_cost int, lookup_cost int")
    serial, piped = (prefetch.makespan(df, p).first()["makespan"] for p in (False, True))
    want = costs[0][0] + sum(max(costs[k][1], costs[k + 1][0] if k + 1 < len(costs) else 0) for k in range(len(costs)))
    assert serial == sum(map(sum, costs)) and piped == want <= serial


def test_ahead_keeps_order_and_raises():
    assert list(prefetch.ahead(range(50), 3)) == list(range(50))

    def broken():
        yield 1
        raise KeyError("x")

    with pytest.raises(KeyError):
        list(prefetch.ahead(broken()))


def test_lsm_runs():
    assert [baselines.lsm_runs(d, 4) for d in (0, 3, 4, 16, 30)] == [0, 3, 1, 1, 6]


def test_wall_calibration(spark):
    costs = cost.UnitCosts()
    rows = spark.createDataFrame([("wide", n) for n in (256, 4096, 8192)], "mode string, length int").withColumn("ratio", costs.ratio(F.col("length"), F.col("length")))
    by = {r["length"]: r["ratio"] for r in rows.collect()}
    assert by[4096] == pytest.approx(0.75) and by[256] < by[4096] < by[8192]
    assert cost.wall(rows).first()["wall"] == 8192


def test_ne_of_base_rate_is_one(spark):
    rows = spark.createDataFrame([(k, int(k % 4 == 0), 0.25) for k in range(100)], "k int, label int, p double")
    assert quality.ne(rows.withColumn("g", F.lit(1)), ["g"]).first()["ne"] == pytest.approx(1.0)
    assert quality.ne_gain(1.0, 0.99) == pytest.approx(0.01)


def test_asof_and_salted(spark):
    rnd = random.Random(1)
    left = [(k, rnd.randint(0, 3), rnd.randint(0, 50)) for k in range(60)]
    right = [(rnd.randint(0, 3), rnd.randint(0, 50), k) for k in range(60)]
    a, b = spark.createDataFrame(left, "id int, k int, t int"), spark.createDataFrame(right, "k int, u int, v int")
    got = {r["id"]: r["v"] for r in joins.asof(a, b.dropDuplicates(["k", "u"]), "k", "t", "u", "v").collect()}
    kept = {(r["k"], r["u"]): r["v"] for r in b.dropDuplicates(["k", "u"]).collect()}
    for i, k, t in left:
        near = [u for kk, u in kept if kk == k and u <= t]
        assert got[i] == (kept[(k, max(near))] if near else None)
    assert joins.salted(a, b, "k", 5).count() == a.join(b, "k").count()
