"""The stages against brute force on a small fixture."""

import random
import re
from collections import Counter, defaultdict

import corpus_pipeline
import pytest

from histreplay.llm.registry import SOURCE_WEIGHTS
from tests.llm.test_operators import SF, WORD, brute_near, brute_targets
from histreplay.llm import mixing


@pytest.fixture(scope="module")
def rows():
    rnd = random.Random(9)
    vocab = ["".join(rnd.choices("abcdefghij", k=rnd.randint(2, 7))) for _ in range(400)]
    prose = lambda n: " ".join(rnd.choices(vocab, k=n))
    out = [(k, prose(rnd.randint(20, 120)), "en", f"s{k % 3}") for k in range(60)]
    base = prose(100)
    out += [(100 + k, base, "en", "s0") for k in range(5)] + [(200 + k, base + f" tail{k}", "en", "s1") for k in range(5)]
    return out + [(300, None, "en", "s0"), (301, "", None, None), (302, "123 456", "en", "s2")]


def stage(spark, name, docs):
    return dict(corpus_pipeline.STAGES)[name](spark, docs, SF)


def frame(spark, rows):
    return spark.createDataFrame([(*r, len(r[1] or "")) for r in rows], "doc_id long, text string, lang string, source string, n_chars long")


def test_stages(spark, rows):
    docs = frame(spark, rows)
    first = stage(spark, "language_id", docs)
    assert first.columns == docs.columns
    assert {r["doc_id"] for r in first.collect()} == {i for i, t, *_ in rows if re.search("[a-z]", t or "")}
    second = stage(spark, "exact_dedup", first)
    best = {}
    for r in first.collect():
        best[r["text"]] = max(best.get(r["text"], -1), r["doc_id"])
    assert Counter(r["doc_id"] for r in second.collect()) == Counter(best.values())
    third = stage(spark, "near_dedup", second)
    kept = [(r["doc_id"], r["text"]) for r in second.collect()]
    roots, _ = brute_near(kept)
    assert {r["doc_id"] for r in third.collect()} == set(roots.values())
    fourth = stage(spark, "mix_sources", third)
    assert fourth.columns == docs.columns
    sizes, taken = defaultdict(int), defaultdict(int)
    for r in third.collect():
        sizes[r["source"]] += len(WORD.findall(r["text"]))
    for r in fourth.collect():
        taken[r["source"]] += len(WORD.findall(r["text"]))
    want = brute_targets(sizes, mixing.weights_in_order(list(sizes), SOURCE_WEIGHTS), sum(sizes.values()), 3)
    assert all(abs(taken[s] - want[s]) <= 1 for s in sizes)
    fifth = stage(spark, "pack", fourth)
    assert {r["doc_id"] for r in fifth.collect()} == {r["doc_id"] for r in fourth.collect()}


def test_empty(spark, rows):
    docs = frame(spark, rows).limit(0)
    for name, _ in corpus_pipeline.STAGES:
        assert stage(spark, name, docs).count() == 0


def test_language_stage_rejects_letter_junk(spark):
    rnd = random.Random(12)
    vocab = ["".join(rnd.choices("abcdefghij", k=rnd.randint(2, 7))) for _ in range(400)]
    clean = [(k, " ".join(rnd.choices(vocab, k=rnd.randint(60, 120))), "en", "s0") for k in range(200)]
    junk = [(1000 + k, " ".join("".join(rnd.choices("klmnopqrstuvwxyz", k=rnd.randint(2, 9))) for _ in range(90)), None, "s0") for k in range(20)]
    assert {r["doc_id"] for r in stage(spark, "language_id", frame(spark, clean + junk)).collect()} == {r[0] for r in clean}


def test_language_stage_keeps_letters_when_nothing_is_learned(spark):
    rows = [(k, f"some text {k}", None, "s0") for k in range(20)] + [(99, "123", None, "s0")]
    assert {r["doc_id"] for r in stage(spark, "language_id", frame(spark, rows)).collect()} == set(range(20))


def test_pack_stage_packs_as_op9_does(spark, rows, monkeypatch):
    seen = []
    monkeypatch.setattr(corpus_pipeline.packing, "pack", lambda docs, *a, **k: seen.append(k) or docs.withColumnRenamed("doc_id", "id"))
    stage(spark, "pack", frame(spark, rows))
    assert seen == [{}]


def test_stages_leave_only_their_last_table(spark):
    from histreplay.llm import common

    before = common.written()
    corpus_pipeline.run(spark, SF).count()
    kept = common._written[before:]
    assert any("mix_sources" in x for x in kept) and not any(n in x for x in kept for n in ("language_id", "exact_dedup", "near_dedup", "sketch", "links"))


@pytest.mark.parametrize("name", ["near_dedup", "pack"])
def test_large_stages_begin_with_small_heaps(spark, rows, name):
    """Executors, here the driver's process, collect all their garbage before the stage's own work."""
    beans = list(spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans())
    full = lambda: sum(b.getCollectionCount() for b in beans if "Old" in b.getName() or "MarkSweep" in b.getName())
    docs, before = frame(spark, rows), full()
    stage(spark, name, docs)
    assert full() > before
