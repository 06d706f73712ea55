"""Each operator against brute force, and on odd inputs."""

import binascii
import hashlib
import json
import math
import random
import re
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers as P
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from histreplay.llm import common, exact_dedup, lang_id, license_scan, mixing, near_dedup, packing, quality_resample, quality_rules, sharding, token_codes, tokenise
from histreplay.llm.common import join_groups, with_prefix_sums
from histreplay.llm.components import components
from histreplay.llm.registry import SOURCE_WEIGHTS, queries
from histreplay.llm.tokenise import Encoder, encoder, forget

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, id long, size int, rank string, kept string, bucket int, score string, n long, shard int"


def table(spark, rows):
    """Documents with further columns whose names operators use inside."""
    return spark.createDataFrame([(i, t, g, s, 0, 7, 1, "r", "k", 3, "s", 9, 5) for i, t, g, s in rows], SCHEMA)


@pytest.fixture(scope="module")
def odd_rows():
    rnd = random.Random(4)
    words = ["alpha", "beta", "gamma", "delta", "eins", "zwei", "über", "naïve", "MIT", "License"]
    prose = lambda n: " ".join(rnd.choices(words, k=n))
    base = prose(120)
    rows = [(k, prose(rnd.randint(1, 80)), rnd.choice(["en", "de", None]), rnd.choice(["a", "b", "ü", None])) for k in range(40)]
    rows += [(50, None, None, None), (51, "", "en", "a"), (52, " \n\t ", "en", "a"), (53, "日本語 テキスト", "ja", "b"), (54, "1 2 3 !!", "en", "b"), (55, prose(30_000), "en", "a")]
    rows += [(60 + k, base, "en", "a") for k in range(6)] + [(70, base + " end", "en", "b"), (71, base.upper(), "en", "b")]
    return rows + [(80, "same row", "en", "a")] * 3 + [(None, "no id", "en", "a"), (None, base, None, None)]


@pytest.fixture(scope="module")
def odd(spark, odd_rows):
    return table(spark, odd_rows)


@pytest.fixture(scope="module")
def none(spark):
    return table(spark, [])


@pytest.fixture(scope="module")
def labels(spark, odd_rows):
    return spark.createDataFrame([(k, int(k % 3 > 0), 0) for k in range(60)] + [(1, 1, 0), (None, 1, 0)], "doc_id long, quality int, toxic int")


def test_prefix_sums(spark):
    rnd = random.Random(2)
    rows = [(rnd.choice(["x", None]), rnd.randint(0, 3), k, rnd.randint(0, 9)) for k in range(100)]
    df = spark.createDataFrame(rows, "g string, bucket int, k int, v int")
    got = {r["k"]: r["before"] for r in with_prefix_sums(df, ["g"], "bucket", [F.col("k")], {"v": "before"}).collect()}
    for g, b, k, _ in rows:
        assert got[k] == sum(v for gg, bb, kk, v in rows if gg == g and (bb, kk) < (b, k))


def test_join_groups_with_hot_key(spark):
    rows = spark.range(3000).select(F.when(F.col("id") < 2000, 0).otherwise(F.col("id")).alias("key"), "id")
    groups = rows.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1 or key % 2 = 0")
    got = join_groups(rows, groups, ["key"], "n")
    assert got.count() == 3000 and got.filter("n = 2000").count() == 2000 and got.filter("n is null").count() == 500


def test_release(spark):
    from histreplay.llm import common

    df = common.stored(spark.range(3).toDF("id"), "gone")
    path = common._written[-1]
    assert df.count() == 3 and common.release(spark) > 0 and common.release(spark) == 0
    with pytest.raises(Exception):
        spark.read.parquet(path).count()


def test_components(spark):
    rnd = random.Random(5)
    links = [(rnd.randint(0, 200), rnd.randint(0, 200)) for _ in range(150)] + [(300 + k, 301 + k) for k in range(60)]
    parent = list(range(400))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        parent[b] = a
    got = {r["id"]: r["root"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    want = {x: find(x) for a, b in links if a != b for x in (a, b)}
    assert got == want


def test_language(spark, odd, none):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    found = queries()["op1_hypervector_language"](spark, SF).join(docs.select("doc_id", "lang", "text"), "doc_id")
    rows = found.collect()
    assert len(rows) == docs.count()
    for r in rows:
        assert r["held_out"] == (binascii.crc32(str(r["doc_id"]).encode()) % 4 == 2)
        assert 0 <= r["score"] <= 1
    held = [r["lang_pred"] == r["lang"] for r in rows if r["held_out"]]
    assert sum(held) / len(held) > 0.95
    got = {(r["id"], r["lang_pred"]) for r in lang_id.identify(odd).collect()}
    assert {(50, "und"), (51, "und"), (52, "und"), (54, "und")} <= got
    assert lang_id.identify(none).count() == 0
    kept = lang_id.keep_identified(odd)
    assert kept.columns == odd.columns and kept.filter("doc_id in (50, 51, 52, 54)").count() == 0 and kept.count() == odd.count() - 4


def test_cosines_by_brute_force(spark):
    """Predictions again from letter vectors, bound by rotation and bundled in plain loops."""
    spec = lang_id.LangSpec(dims=64)
    rows = [(0, "ein kleiner Hund", "de"), (1, "the small dog", "en"), (3, "der grosse Baum!", "de"), (4, "a tall tree 7", "en"), (5, "eine kleine Maus", None), (7, "Größe", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    items = lang_id.Memory(spec).items.astype(int)

    def vector(text):
        p, out = lang_id.letters(text), np.zeros(spec.dims)
        for x, y, z in zip(p, p[1:], p[2:]):
            out += [items[x][(k - 2) % spec.dims] * items[y][(k - 1) % spec.dims] * items[z][k] for k in range(spec.dims)]
        return out / np.linalg.norm(out)

    prototypes = {g: sum(vector(t) for _, t, own in rows if own == g) for g in ("de", "en")}
    got = lang_id.predict(docs, lang_id.learn(docs, spec), spec).collect()
    for r, (_, text, _) in zip(sorted(got, key=lambda r: r["doc_id"]), rows):
        cosine = {g: float(vector(text) @ v / np.linalg.norm(v)) for g, v in prototypes.items()}
        best = max(cosine, key=cosine.get)
        assert r["lang_pred"] == best and r["score"] == pytest.approx(max(0, cosine[best]), abs=1e-4)


def test_language_does_not_read_other_columns(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    spoiled = docs.withColumn("lang", F.when(lang_id.held_out(), "xx").otherwise(F.col("lang"))).withColumn("source", F.lit("z"))
    a, b = (x.orderBy("id").collect() for x in (lang_id.identify(docs), lang_id.identify(spoiled)))
    assert a == b


def test_resampling(spark, odd, none, labels):
    got = quality_resample.resample(odd, labels).collect()
    assert sorted(r["rank"] for r in got) == list(range(odd.count()))
    by_rank = sorted(got, key=lambda r: r["rank"])
    assert all(a["key"] >= b["key"] for a, b in zip(by_rank, by_rank[1:]))
    assert sum(r["kept"] for r in got) == round(0.9 * odd.count())
    assert quality_resample.resample(none, labels).count() == 0
    ratios = quality_resample.learn(odd, labels.limit(0))
    assert not ratios.any()


def test_resampling_weights_by_brute_force(spark, odd_rows, odd, labels):
    spec = quality_resample.ResampleSpec(buckets=50)
    ratios = quality_resample.learn(odd, labels, spec)
    assert len(ratios) == 50 and np.isfinite(ratios).all()
    got = {r["id"]: r for r in quality_resample.weigh(odd, ratios, spec).collect()}
    for i, text, *_ in odd_rows:
        if i is not None:
            n = len(WORD.findall(text or ""))
            assert got[i]["n_grams"] == max(0, 2 * n - 1)


def test_generative_ratios_by_brute_force(spark):
    """Log ratios and document weights from plain counts of words and word pairs, where no two share a bucket."""
    rnd = random.Random(8)
    rows = [(k, " ".join(rnd.choices(["ab", "cd", "ef", "gh"], k=rnd.randint(0, 12))), "en", "a") for k in range(60)] + [(99, None, "en", "a")]
    good = {k for k in range(0, 60, 3)}
    spec = quality_resample.ResampleSpec(buckets=1 << 20)
    docs, marks = table(spark, rows), spark.createDataFrame([(k, int(k in good)) for k in range(40)], "doc_id long, quality int")
    grams = lambda t: (w := (t or "").split()) + list(zip(w, w[1:]))
    raw, target = Counter(), Counter()
    for k, t, *_ in rows:
        raw.update(grams(t))
        target.update(grams(t) if k in good and k < 40 else [])
    chance = lambda c, g: math.log((c[g] + 1) / (sum(c.values()) + spec.buckets))
    got = {r["id"]: r["log_ratio"] for r in quality_resample.resample(docs, marks, spec).collect()}
    for k, t, *_ in rows:
        assert got[k] == pytest.approx(sum(chance(target, g) - chance(raw, g) for g in grams(t)), abs=1e-9)


def test_resampling_spreads_texts_without_words(spark):
    docs = table(spark, [(k, " " * (k % 3), "en", "a") for k in range(200)])
    got = quality_resample.resample(docs, spark.createDataFrame([(1, 1)], "doc_id long, quality int")).collect()
    assert len({r["key"] for r in got}) == 200 and sum(r["kept"] for r in got) == 180


def brute_targets(sizes, weights, total, most):
    low, high = 0.0, 1e12
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if sum(min(most * sizes[s], mid * weights[s]) for s in sizes) < total else (low, mid)
    return {s: min(most * sizes[s], low * weights[s]) for s in sizes}


def test_mixing(odd_rows, odd, none):
    got = mixing.mix(odd, SOURCE_WEIGHTS).collect()
    assert len(got) == len(odd_rows)
    sizes = defaultdict(int)
    for _, text, _, source in odd_rows:
        sizes[source] += len(WORD.findall(text or ""))
    weights = mixing.weights_in_order(list(sizes), SOURCE_WEIGHTS)
    assert [weights[s] for s in ("a", "b", "ü", None)] == [5, 2, 1, 5]
    want = brute_targets(sizes, weights, sum(sizes.values()), 3)
    taken = defaultdict(int)
    for r in got:
        assert r["source_size"] == sizes[r["source"]]
        assert math.isclose(r["target"], want[r["source"]], rel_tol=1e-6)
        assert 0 <= r["taken"] <= 3 * r["size"] and r["taken"] >= r["epochs"] * r["size"]
        taken[r["source"]] += r["taken"]
    assert all(abs(taken[s] - want[s]) <= 1 for s in sizes)
    assert sorted(map(str, mixing.mix(odd, SOURCE_WEIGHTS).collect())) == sorted(map(str, got))
    assert mixing.mix(none, SOURCE_WEIGHTS).count() == 0


def test_mixing_order_is_by_exponential_keys(odd):
    rows = [r for r in mixing.mix(odd, SOURCE_WEIGHTS).collect() if r["size"]]
    for source in {r["source"] for r in rows}:
        own = sorted((r for r in rows if r["source"] == source), key=lambda r: (r["key"], r["id"] or -1))
        parts = [r["part"] / r["size"] for r in own]
        assert parts == sorted(parts, reverse=True)


def test_mixed_documents(odd, none):
    out = mixing.mixed_documents(odd, SOURCE_WEIGHTS)
    assert out.columns == odd.columns
    words = {r["source"]: r["n"] for r in out.groupBy("source").agg(F.sum(mixing.n_words(F.col("text"))).alias("n")).collect()}
    want = {r["source"]: r["n"] for r in mixing.mix(odd, SOURCE_WEIGHTS).groupBy("source").agg(F.sum("taken").alias("n")).collect()}
    for s, n in words.items():
        assert n == want[s]
    assert mixing.mixed_documents(none, SOURCE_WEIGHTS).count() == 0


def test_mixed_documents_of_repeated_rows(spark):
    """Rows that repeat id, source and text, or only id and size, are taken as often as planned."""
    rows = [(1, "a b c d e", "en", "x")] * 5 + [(1, "f g h i j", "en", "x")] * 2 + [(2, "k l m", "en", "y"), (3, None, "en", "y"), (None, "n o", "en", "x"), (None, "n o", "en", None)]
    docs = table(spark, rows)
    for weights in (SOURCE_WEIGHTS, (1.0, 30.0)):
        plan, got = mixing.mix(docs, weights), mixing.mixed_documents(docs, weights)
        want = {(r["id"], r["source"], r["text_hash"]): r["n"] for r in plan.groupBy("id", "source", "text_hash").agg(F.sum("taken").alias("n")).filter("n > 0").collect()}
        assert sum(r["n"] for r in got.select(mixing.n_words(F.col("text")).alias("n")).collect()) == sum(want.values())
        by_source = Counter()
        for (_, source, _), n in want.items():
            by_source[source] += n
        assert Counter({r["source"]: r["n"] for r in got.groupBy("source").agg(F.sum(mixing.n_words(F.col("text"))).alias("n")).collect()}) == by_source


CLASHING = ("key", "whole", "cut", "again", "k", "hash", "id_of", "bytes", "n_bytes", "prefix", "shard_", "Key_", "__id", "__src", "__hash", "full_hash", "epochs", "lang_pred", "text_hash")


def test_extra_columns_of_any_name_pass_through(spark, odd_rows, tmp_path):
    docs = table(spark, odd_rows)
    for name in CLASHING:
        docs = docs.withColumn(name, F.lit(f"own {name}"))
    want = {name: f"own {name}" for name in CLASHING}
    for keep in (lang_id.keep_identified, exact_dedup.drop_exact_duplicates, near_dedup.drop_near_duplicates, lambda d: mixing.mixed_documents(d, SOURCE_WEIGHTS)):
        out = keep(docs)
        assert out.columns == docs.columns
        rows = out.collect()
        assert rows and all({n: r[n] for n in CLASHING} == want and r["rank"] == "r" and r["shard"] == 5 for r in rows)
    folder = sharding.write_shards(docs, str(tmp_path / "out"), 4)
    assert folder == "shard__" and spark.read.parquet(str(tmp_path / "out")).filter("shard = 5").count() == docs.count()


@pytest.mark.parametrize("n", [0, 1, 8, 511, 512, 513, 4000])
def test_codes_round_trip(n):
    rnd = np.random.default_rng(n)
    ids = (rnd.integers(0, 1 << 32, n) >> rnd.integers(0, 32, n)).astype(np.uint32)
    codes = token_codes.Codes(token_codes.encode_codes(ids))
    assert (codes.decode() == ids).all() and len(codes) == n
    assert all(codes[k] == ids[k] for k in range(n))
    with pytest.raises(IndexError):
        codes[n]


@pytest.mark.parametrize(("name", "kind"), [("byte_bpe_50k.json", "byte_level"), ("word_bpe_49k.json", "word_level")])
def test_encoder_equals_library(name, kind):
    rnd = random.Random(6)
    letters = [chr(k) for k in range(256)] + list("   ''stremdaé\n") + ["<|endoftext|>", "ł", "日", "\x85"]
    texts = ["".join(rnd.choices(letters, k=rnd.randint(0, 40))) for _ in range(3000)]
    own = Encoder(P.path(name), kind)
    for text, got in zip(texts, own.encode(texts)):
        assert np.frombuffer(got, "<u4").tolist() == own.library.encode(text, add_special_tokens=False).ids


def test_token_files(spark, odd_rows, odd, none):
    lib = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    path = token_codes.token_files(odd, P.path("byte_bpe_50k.json"))
    got = sorted(token_codes.read_documents(spark, path).collect(), key=lambda r: r["start"])
    codes = lambda text: np.array([*lib.encode(text or "", add_special_tokens=False).ids, 0], "<u2").tobytes()
    order = sorted(odd_rows, key=lambda r: (r[0] is not None, r[0] or 0, codes(r[1])))
    at = 0
    for r, (i, text, *_) in zip(got, order, strict=True):
        ids = np.array([*lib.encode(text or "", add_special_tokens=False).ids, 0], "<u4")
        assert (r["id"], r["start"], r["n_tokens"], r["ids_crc32"]) == (i, at, len(ids), binascii.crc32(ids.tobytes()))
        at += len(ids)
    every = [x for _, text, *_ in order for x in (*lib.encode(text or "", add_special_tokens=False).ids, 0)]
    for place, count in ((0, 3), (at // 2, 40_000), (at - 2, 10), (at, 5)):
        found = sorted(map(tuple, token_codes.read_tokens(spark, path, place, count).collect()))
        assert found == [(k, every[k]) for k in range(place, min(at, place + count))]
    assert token_codes.read_documents(spark, token_codes.token_files(none, P.path("byte_bpe_50k.json"))).count() == 0


def rows_scanned(df):
    """Rows that the file scan of a collected frame handed on."""
    (leaf,) = (x for x in [df._jdf.queryExecution().executedPlan().collectLeaves().apply(0)])
    return leaf.metrics().get("numOutputRows").get().value()


def test_a_token_is_read_without_reading_the_files(spark):
    rnd = random.Random(3)
    words = [("".join(rnd.choices("abcdefghijklmnopqrstuvwxyz", k=6))) for _ in range(3000)]
    rows = [(k, " ".join(rnd.choices(words, k=1000)), "en", "a") for k in range(1500)]
    path = token_codes.token_files(table(spark, rows).coalesce(1), P.path("byte_bpe_50k.json"))
    segments = token_codes._segments(spark, path).count()
    one = token_codes.read_tokens(spark, path, 1_000_000, 1)
    assert one.count() == 1 and len(one.collect()) == 1
    assert segments > 200 and rows_scanned(one) <= 2 * token_codes.PAGE_ROWS


@pytest.mark.parametrize(("name", "kind"), [("byte_bpe_50k.json", "byte_level"), ("word_bpe_49k.json", "word_level")])
def test_encoder_equals_library_on_whole_documents(spark, name, kind):
    texts = [r["text"] for r in spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("text").collect() if r["text"]]
    own = Encoder(P.path(name), kind)
    want = own.library.encode_batch_fast(texts, add_special_tokens=False)
    for k in range(0, len(texts), 256):
        for got, e in zip(own.encode(texts[k : k + 256]), want[k : k + 256]):
            assert np.frombuffer(got, "<u4").tolist() == e.ids


def test_encoder_leaves_other_vocabularies_to_the_library(tmp_path):
    own = json.loads(open(P.path("word_bpe_49k.json"), encoding="utf-8").read())
    own["normalizer"] = {"type": "NFC"}
    (tmp_path / "own.json").write_text(json.dumps(own), encoding="utf-8")
    enc = Encoder(str(tmp_path / "own.json"), "word_level")
    text = "Some Words, 123 and  more"
    assert np.frombuffer(enc.encode([text])[0], "<u4").tolist() == enc.library.encode(text, add_special_tokens=False).ids


@pytest.mark.parametrize("every", [True, False])
def test_exact(odd_rows, odd, none, every):
    got = exact_dedup.exact_duplicates(odd, hash_all=every).collect()
    groups = defaultdict(list)
    for i, text, *_ in odd_rows:
        groups[text or ""].append(i)
    want = Counter()
    for ids in groups.values():
        keep = max((i for i in ids if i is not None), default=None)
        for i in ids:
            want[(i, keep if len(ids) > 1 else i, len(ids), (i == keep) or len(ids) == 1)] += 1
    assert Counter((r["id"], r["keep_id"], r["group_size"], r["kept"]) for r in got) == want
    if every:
        assert {r["full_hash"] for r in got} == {hashlib.sha256(t.encode()).hexdigest() for t in groups}
    assert exact_dedup.exact_duplicates(none, hash_all=every).count() == 0


def test_drop_exact(odd_rows, odd):
    kept = exact_dedup.drop_exact_duplicates(odd)
    assert kept.columns == odd.columns
    assert Counter(r["text"] or "" for r in kept.collect()) == Counter({t or "": 1 for _, t, *_ in odd_rows})


def brute_near(rows):
    sets = []
    for _, text, *_ in rows:
        w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        sets.append({tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set())
    parent = {i: i for i, *_ in rows if i is not None}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for x in range(len(rows)):
        for y in range(x):
            if rows[x][0] is not None and rows[y][0] is not None and sets[x] and sets[y]:
                both = len(sets[x] & sets[y])
                if 100 * both >= 75 * (len(sets[x]) + len(sets[y]) - both):
                    a, b = sorted((find(rows[x][0]), find(rows[y][0])))
                    parent[b] = a
    return {i: find(i) for i in parent}, [len(s) for s in sets]


def test_near(odd_rows, odd, none):
    got = near_dedup.near_duplicates(odd).collect()
    roots, sizes = brute_near(odd_rows)
    assert Counter((r["id"], r["n_shingles"], r["component_id"], r["kept"]) for r in got) == Counter((i, n, roots.get(i), i is None or roots[i] == i) for (i, *_), n in zip(odd_rows, sizes))
    assert near_dedup.near_duplicates(none).count() == 0
    kept = near_dedup.drop_near_duplicates(odd)
    assert kept.columns == odd.columns and kept.filter("doc_id between 61 and 70").count() == 0 and kept.filter("doc_id is null").count() == 2


def test_near_links_every_text_of_an_id(spark):
    """Rows that repeat an id with different texts: each text's links count, and all join under the id."""
    rnd = random.Random(17)
    prose = lambda: " ".join(f"w{rnd.randint(0, 10**6)}" for _ in range(100))
    a, b, c = prose(), prose(), prose()
    rows = [(1, a), (1, b), (2, a + " x"), (3, b + " y"), (4, c), (5, c), (5, b), (6, prose()), (7, a), (7, a), (8, None), (8, c + " z"), (9, None), (0, prose()), (0, prose())]
    rows = [(*r, None, None) for r in rows]
    got = near_dedup.near_duplicates(table(spark, rows)).collect()
    roots, sizes = brute_near(rows)
    assert Counter((r["id"], r["n_shingles"], r["component_id"], r["kept"]) for r in got) == Counter((i, n, roots[i], roots[i] == i) for (i, *_), n in zip(rows, sizes))
    assert roots[2] == roots[3] == roots[8] == 1 and roots[9] == 9 and roots[0] == 0


def test_near_family(spark):
    """A family of copies that are far from each other but near to a base: large buckets and blocks."""
    rnd = random.Random(8)
    base = [f"w{rnd.randint(0, 500)}" for _ in range(150)]
    rows = [(1000, " ".join(base), None, None)]
    for k in range(120):
        own = list(base)
        for _ in range(rnd.randint(1, 6)):
            own[rnd.randrange(len(own))] = f"x{rnd.randint(0, 10**6)}"
        rows.append((k, " ".join(own), None, None))
    roots, _ = brute_near(rows)
    spec = near_dedup.NearDupSpec(split=4, block_bytes=20_000)
    got = {r["id"]: r["component_id"] for r in near_dedup.near_duplicates(table(spark, rows), spec=spec).collect()}
    assert got == roots


def test_block_links_leave_no_component_apart():
    rnd = np.random.default_rng(3)
    base = rnd.integers(0, 1 << 60, 60).astype(np.uint64)
    sets = [np.unique(np.concatenate([base[rnd.permutation(60)[:52]], rnd.integers(0, 1 << 60, 4).astype(np.uint64)])) for _ in range(50)]
    ids, parent = np.arange(50), list(range(50))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in near_dedup.block_links(ids, ids, sets, np.zeros(50, int), 75):
        parent[find(b)] = find(a)
    for x in range(50):
        for y in range(x):
            both = len(np.intersect1d(sets[x], sets[y]))
            if 100 * both >= 75 * (len(sets[x]) + len(sets[y]) - both):
                assert find(x) == find(y)


def test_sharding(spark, odd_rows, odd, none):
    got = sharding.shard_documents(odd, 8).collect()
    assert len(got) == len(odd_rows)
    for r in got:
        assert r["grown_shard"] in (r["shard"], 8) and 0 <= r["shard"] < 8
    want = Counter((i, len((t or "").encode()) + 1, binascii.crc32((t or "").encode())) for i, t, *_ in odd_rows)
    assert Counter((r["id"], r["size"], r["text_crc32"]) for r in got) == want
    for s in range(8):
        slots = sorted(r["slot"] for r in got if r["shard"] == s)
        assert slots == list(range(len(slots)))
    assert sharding.shard_documents(none, 8).count() == 0
    keys = spark.range(4000).select(F.col("id").cast("string").alias("k"))
    for n in (1, 2, 7, 8, 20):
        moved = keys.select(sharding.jump_shard(F.col("k"), n).alias("a"), sharding.jump_shard(F.col("k"), n + 1).alias("b"))
        assert moved.filter("a <> b and b <> " + str(n)).count() == 0
        share = moved.filter("a <> b").count() / 4000
        assert abs(share - 1 / (n + 1)) < 0.04
    with pytest.raises(ValueError):
        sharding.jump_shard(F.col("k"), 0)


def test_jumps_equal_the_plain_algorithm(spark):
    """The same draws through the textbook loop."""

    def jump(key, shards):
        b, j, k = -1, 0, 0
        while j < shards:
            k += 1
            b = j
            u = (int(hashlib.md5(f"{key}:{k}".encode()).hexdigest()[:8], 16) + 1) / 2**32
            j = math.floor((b + 1) / u)
        return b

    keys = spark.range(500).select(F.col("id").cast("string").alias("k"))
    for shards in (1, 2, 8, 9, 100, 1000):
        got = keys.select("k", sharding.jump_shard(F.col("k"), shards).alias("s")).collect()
        assert all(r["s"] == jump(r["k"], shards) for r in got)


def test_shards_written_are_those_told(spark, odd, odd_rows, tmp_path):
    name = sharding.write_shards(odd, str(tmp_path / "told"), 8)
    found = odd.sparkSession.read.parquet(str(tmp_path / "told")).select("doc_id", F.crc32(F.coalesce("text", F.lit("")).cast("binary")).alias("crc"), name).collect()
    told = sharding.shard_documents(odd, 8).select("id", "text_crc32", "shard").collect()
    assert Counter(map(tuple, found)) == Counter(map(tuple, told))


def test_write_shards(odd, tmp_path):
    sharding.write_shards(odd.drop("shard"), str(tmp_path / "out"), 4)
    assert odd.sparkSession.read.parquet(str(tmp_path / "out")).count() == odd.count()


def brute_rules(text):
    w = WORD.findall(text)
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    c, cover = Counter(zip(w, w[1:], w[2:])), set()
    for k in range(len(w) - 2):
        if c[tuple(w[k : k + 3])] > 1:
            cover |= {k, k + 1, k + 2}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(cover)


def test_rules(odd_rows, odd, none, labels):
    got = quality_rules.judge(odd, labels).collect()
    want = Counter((i, *brute_rules(t or "")) for i, t, *_ in odd_rows)
    assert Counter((r["id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) for r in got) == want
    for r in got:
        assert r["base_failed"] == (r["n_words"] < 50 or 100 * r["n_repeat_words"] > 50 * r["n_words"])
        assert not (r["base_failed"] and r["kept"])
    assert quality_rules.judge(none, labels).count() == 0
    assert all(r["rejected_by"] == "" for r in quality_rules.judge(odd, labels.limit(0)).collect())


def test_lines(spark):
    texts = ["a\na\n\n\na b\na", "x\n x\nx \nx", "", "\n\n", "one", "a\r\na\r\na"]
    rows = quality_rules.measures(table(spark, [(k, t, "en", "a") for k, t in enumerate(texts)])).collect()
    assert {r["id"]: r["n_dup_lines"] for r in rows} == {k: brute_rules(t)[3] for k, t in enumerate(texts)}


def test_binomial_bound():
    assert quality_rules.upper_bound(0, 100, 0.05) == pytest.approx(1 - 0.05 ** (1 / 100), rel=1e-6)
    for k, n in ((1, 50), (3, 80), (10, 400)):
        p = quality_rules.upper_bound(k, n, 0.01)
        assert sum(math.comb(n, j) * p**j * (1 - p) ** (n - j) for j in range(k + 1)) == pytest.approx(0.01, rel=1e-6)
    assert quality_rules.upper_bound(5, 5, 0.1) == 1.0


def test_rules_find_cutoffs_and_keep_the_good(spark):
    good = [(k, " ".join(f"word{j}x{k}" for j in range(60)), "en", "a") for k in range(1500)]
    bad = [(2000 + k, " ".join(f"###word{j}{k}!!" for j in range(60)), "en", "a") for k in range(200)]
    marks = spark.createDataFrame([(i, int(i < 2000)) for i, *_ in good + bad], "doc_id long, quality int")
    got = quality_rules.judge(table(spark, good + bad), marks).collect()
    kept = {r["id"]: r["kept"] for r in got}
    assert all(kept[i] for i, *_ in good) and not any(kept[i] for i, *_ in bad)


def test_rules_verdict_by_brute_force(spark):
    """Cutoffs, bound and verdict again, step by step in plain Python."""
    rnd = random.Random(21)
    marks = lambda share, n: " ".join(("#" if rnd.random() < share else "") + rnd.choice("abcdefgh") * rnd.randint(2, 9) for _ in range(n))
    rows, quality = [], {}
    for k in range(900):
        lang = ("en", "de", None)[k % 3]
        bad = rnd.random() < 0.2
        rows.append((k, marks(0.3 if bad else 0.02, 80 + k % 40), lang, "a"))
        if rnd.random() < 0.6:
            quality[k] = int(not bad)
    spec = quality_rules.RiskSpec()
    own = {k: [float(x) for x in quality_measures(t)] for k, t, *_ in rows}
    stratum = {k: g or "none" for k, _, g, _ in rows}
    rejected = dict.fromkeys(own, False)
    counts, seen, cuts, paths = {}, {}, {}, {}
    for s in ("en", "de", "none"):
        others = [k for k in own if stratum[k] == s and quality.get(k) != 1]
        cuts[s] = [[sorted(own[k][r] for k in others)[max(0, math.ceil((1 - spec.tail * t) * len(others)) - 1)] for t in range(1, spec.steps + 1)] for r in range(6)]
        level = lambda k, r, s=s: next((t for t in range(spec.steps) if own[k][r] > 0 and own[k][r] >= cuts[s][r][t]), spec.steps)
        bad = {n: [0] * (spec.steps + 1) for n, _ in quality_rules.RULES}
        for k in others:
            if quality.get(k) == 0:
                for r, (n, _) in enumerate(quality_rules.RULES):
                    bad[n][level(k, r)] += 1
        paths[s] = quality_rules.joint_path(bad, spec)
        good = [k for k in own if stratum[k] == s and quality.get(k) == 1]
        counts[s] = [sum(any(level(k, r) < x for r, x in enumerate(levels)) for k in good) for levels in paths[s]]
        seen[s] = len(good)
    proven = quality_rules.certify(counts, seen, spec)
    assert proven
    for k in own:
        if stratum[k] in proven:
            levels = paths[stratum[k]][proven[stratum[k]][0] - 1]
            rejected[k] = any(x and own[k][r] > 0 and own[k][r] >= cuts[stratum[k]][r][x - 1] for r, x in enumerate(levels))
    got = quality_rules.judge(table(spark, rows), spark.createDataFrame(list(quality.items()), "doc_id long, quality int"), spec).collect()
    assert {r["id"]: r["kept"] for r in got} == {k: not x and not r_base(t) for (k, t, *_), x in zip(rows, rejected.values())}
    assert any(rejected.values())


def quality_measures(text):
    """The rules' measures in plain Python."""
    n, chars, symbols, dup, repeat = brute_rules(text)
    lines = sum(bool(WORD.search(x)) for x in text.split("\n"))
    marks = sum(33 <= ord(c) < 127 and not c.isalnum() for c in text)
    return symbols / max(n, 1), marks / max(n, 1), sum("A" <= c <= "Z" for c in text) / max(chars, 1), chars / max(n, 1) / 40, dup / max(lines, 1), repeat / max(n, 1)


def r_base(text):
    n, *_, repeat = brute_rules(text)
    return n < 50 or 100 * repeat > 50 * n


def test_false_rejections_pass_the_risk_in_few_runs():
    """Good documents drawn from known chances: how often does any stratum's chosen step reject more than the risk?"""
    rnd = np.random.default_rng(0)
    spec = quality_rules.RiskSpec(risk=0.05, miss=0.1)
    truth = np.concatenate([[0.02, 0.04, 0.049], np.linspace(0.0505, 0.3, 57)])
    failed, acted = 0, 0
    for _ in range(600):
        sizes = {f"s{k}": int(n) for k, n in enumerate(rnd.integers(60, 800, 4))}
        at = {s: np.searchsorted(truth, rnd.random(n), "right") for s, n in sizes.items()}
        found = quality_rules.certify({s: [int((x <= t).sum()) for t in range(60)] for s, x in at.items()}, sizes, spec)
        acted += bool(found)
        failed += any(truth[step - 1] > spec.risk for step, _ in found.values())
        assert all(bound <= spec.risk + 1e-9 for _, bound in found.values())
    assert acted > 300 and failed <= 600 * spec.miss + 3 * (600 * spec.miss * (1 - spec.miss)) ** 0.5


def test_path_follows_what_reaches_bad_documents():
    spec = quality_rules.RiskSpec(steps=4, tail=0.05, lift=2)
    names = [n for n, _ in quality_rules.RULES]
    bad = {n: [0, 0, 0, 0, 10] for n in names} | {names[1]: [2, 5, 0, 0, 3], names[3]: [3, 0, 1, 0, 6]}
    path = quality_rules.joint_path(bad, spec)
    assert path[:2] == [(0, 2, 0, 0, 0, 0), (0, 2, 0, 1, 0, 0)] and path[-1][1] == 4 or path[-1][1] >= 2
    assert quality_rules.joint_path({}, spec) == [(k,) * 6 for k in (1, 2, 3, 4)]


def test_packing(odd_rows, odd, none):
    lib = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    got = packing.pack(odd, P.path("word_bpe_49k.json")).collect()
    pieces = defaultdict(list)
    for r in got:
        pieces[r["id"]].append(r)
    texts = defaultdict(list)
    for i, t, *_ in odd_rows:
        texts[i].append([*lib.encode(t or "", add_special_tokens=False).ids, 2])
    for i, own in texts.items():
        if len(own) == 1:
            parts = sorted(pieces[i], key=lambda r: r["start"])
            assert np.frombuffer(b"".join(r["ids"] for r in parts), "<u4").tolist() == own[0]
            assert all(r["doc_tokens"] == len(own[0]) and 4 * r["length"] == len(r["ids"]) and r["ids_crc32"] == binascii.crc32(r["ids"]) for r in parts)
            assert [r["start"] for r in parts] == [sum(p["length"] for p in parts[:k]) for k in range(len(parts))]
    assert sum(r["length"] for r in got) == sum(len(x) for own in texts.values() for x in own)
    windows = defaultdict(list)
    for r in got:
        windows[r["sequence_id"]].append((r["offset"], r["length"]))
    for own in windows.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= 4096
    assert sum(sum(x for _, x in own) < 4096 for own in windows.values()) <= 1
    assert packing.pack(none, P.path("word_bpe_49k.json")).count() == 0


def test_packing_puts_neighbours_together():
    rnd = np.random.default_rng(1)
    topics = [rnd.integers(100 * t, 100 * t + 60, (8, 100)).astype(np.uint32) for t in range(1, 6)]
    docs = [topics[k % 5][k // 5] for k in range(40)]
    spec = packing.PackSpec(window=800)
    held = defaultdict(set)
    for sequence, _, d, _, _ in packing.fill_windows(docs, spec):
        held[sequence].add(d % 5)
    assert all(len(x) == 1 for x in held.values())


def test_bm25_by_brute_force():
    rnd = np.random.default_rng(2)
    docs = [rnd.integers(0, 40, rnd.integers(5, 60)).astype(np.uint32) for _ in range(30)]
    spec = packing.PackSpec(terms=1000)
    index, mean = packing.Index(docs, spec), np.mean([len(d) for d in docs])
    for seed in range(5):
        score = np.zeros(30)
        for t in set(docs[seed].tolist()):
            df = sum(t in d for d in docs)
            if df < 2:
                continue
            for k, d in enumerate(docs):
                tf = int((d == t).sum())
                score[k] += math.log1p((30 - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (1 - 0.75 + 0.75 * len(d) / mean))
        unused = np.ones(30, bool)
        unused[seed] = False
        got = index.neighbours(seed, unused)
        best = [k for k in np.argsort(-score, kind="stable") if k != seed and score[k] > 0]
        assert np.allclose(score[got], score[best])


def test_bm25_of_the_production_spec_has_all_terms():
    rnd = np.random.default_rng(5)
    docs = [rnd.integers(0, 80, rnd.integers(40, 120)).astype(np.uint32) for _ in range(30)]
    full, index = packing.Index(docs, packing.PackSpec(terms=1000)), packing.Index(docs, packing.PackSpec())
    for seed in range(30):
        unused = np.arange(30) != seed
        assert set(index.query(seed)) == {k for k, t in enumerate(sorted(set(np.concatenate(docs).tolist()))) if t in docs[seed] and sum(t in d for d in docs) > 1}
        assert index.neighbours(seed, unused).tolist() == full.neighbours(seed, unused).tolist()


def test_bm25_takes_statistics_of_all_documents(spark):
    rnd = np.random.default_rng(3)
    docs = [rnd.integers(0, 40, rnd.integers(5, 60)).astype("<u2") for _ in range(30)]
    rows = [(k, len(d), False, bytearray(d.tobytes())) for k, d in enumerate(docs)]
    corpus = packing.corpus_of(spark.createDataFrame(rows, "id long, n long, wide boolean, data binary").repartition(4))
    assert corpus.n == 30 and math.isclose(corpus.mean, np.mean([len(d) for d in docs]))
    assert corpus.df.tolist() == [sum(t in d for d in docs) for t in range(len(corpus.df))]
    spec, part = packing.PackSpec(terms=1000), docs[:6]
    index, mean = packing.Index(part, spec, corpus), corpus.mean
    score = np.zeros(6)
    for t in set(part[0].tolist()):
        df = corpus.df[t]
        for k, d in enumerate(part):
            tf = int((d == t).sum())
            score[k] += math.log1p((30 - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (1 - 0.75 + 0.75 * len(d) / mean))
    unused = np.arange(6) > 0
    got = index.neighbours(0, unused)
    assert got.tolist() == [k for k in np.argsort(-score, kind="stable") if k and score[k] > 0]


def test_packing_deals_like_documents_to_one_shard(spark):
    rnd = random.Random(4)
    topics = [[f"{a}{b}" for b in rnd.sample(["ab", "ce", "di", "fo", "gu", "ha", "ji"], 5)] for a in ("stone", "water", "light", "paper")]
    rows = [(k, " ".join(rnd.choices(topics[k % 4], k=200)), "en", "a") for k in range(80)]
    size = sum(len(t) + 1 for _, t, *_ in rows)
    got = packing.pack(table(spark, rows), P.path("word_bpe_49k.json"), spec=packing.PackSpec(window=512, shard_bytes=size // 8)).collect()
    held = defaultdict(set)
    for r in got:
        held[r["sequence_id"] >> 32].add(r["id"] % 4)
    assert len(held) > 4 and {r["id"] for r in got} == set(range(80))
    assert sum(len(x) == 1 for x in held.values()) >= len(held) - 3


def brute_base(text):
    low = re.sub("[A-Z]", lambda m: m[0].lower(), text)
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    starts, found = [], set()
    for phrase, label in (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl")):
        p = phrase.split()
        hit = [k for k in range(len(w)) if w[k : k + len(p)] == p]
        starts += hit
        if hit:
            found.add(label)
    return len(w), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(found))


LICENSED = [
    "Licensed under the Apache License, Version 2.0.", "the MIT-License: MIT license mit LICENSE", "GNU general\npublic, license version 3 or any later version", "mit licenses; smit license",
    "SPDX-License-Identifier: GPL-2.0-only", "Licensed under CC BY-NC 4.0.", "general public license general public license", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software", "All Rights Reserved", "éMIT License MITé license",
    "BSD 3-Clause License", "apache/license", "nothing here", "released into the public domain",
]


def test_licenses(spark, odd_rows, odd, none):
    rows = odd_rows + [(500 + k, t, "en", "a") for k, t in enumerate(LICENSED)]
    got = license_scan.scan_licenses(table(spark, rows)).collect()
    assert Counter((r["id"], r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) for r in got) == Counter((i, *brute_base(t or "")) for i, t, *_ in rows)
    by = {r["id"]: r for r in got}
    want = {500: "apache,apache-2.0", 501: "mit", 502: "gpl,gpl-3+", 504: "gpl-2.0", 505: "cc-by-nc,cc-by-nc-4.0", 507: "mit", 508: "proprietary", 510: "bsd-3-clause", 512: "", 513: "public-domain"}
    for i, labels in want.items():
        assert by[i]["labels"] == labels, (LICENSED[i - 500], by[i])
    for r in got:
        assert 0 <= r["score"] <= 1 and set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))
        for d in r["detections"]:
            inside = [e for e in r["detections"] if e != d and e["start"] <= d["start"] and e["end"] >= d["end"] and e["priority"] < d["priority"]]
            assert not inside
    assert license_scan.scan_licenses(none).count() == 0


def test_license_rules_equal_plain_regexes(spark):
    """Detections before suppression: every rule by Python's re on the joined words."""
    every = license_scan.rules()
    assert len(every) > 200 and len({r.name for r in every}) == len(every)
    got = {r["id"]: r for r in license_scan.scan_licenses(table(spark, [(k, t, "en", "a") for k, t in enumerate(LICENSED)])).collect()}
    for k, text in enumerate(LICENSED):
        low = re.sub("[A-Z]", lambda m: m[0].lower(), text)
        flat = " " + " ".join(re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)) + " "
        hits = [(m.start(), m.end(), r) for r in every if r.keyword in flat for m in re.finditer(rf"(?<= )(?:{r.pattern})(?= )", flat)]

        def gone(d):
            for e in hits:
                if e is d or not (e[0] <= d[0] and e[1] >= d[1]):
                    continue
                strong = e[2].priority < d[2].priority or (e[2].priority == d[2].priority and e[2].name < d[2].name)
                if (e[2].priority <= d[2].priority) if e[1] - e[0] > d[1] - d[0] else strong:
                    return True
            return False

        want = {(d[2].label, d[2].name, d[0], d[1]) for d in hits if not gone(d)}
        assert {(d["label"], d["rule"], d["start"], d["end"]) for d in got[k]["detections"]} == want


def test_licenses_of_a_text_with_very_many(spark):
    n = 5000
    text = " ".join(["licensed under the apache license version 2.0 or the mit license and then"] * n)
    r = license_scan.scan_licenses(table(spark, [(1, text, "en", "a")])).first()
    assert (r["n_base"], r["first_word"], len(r["detections"])) == (2 * n, 3, 3 * n) and r["labels"] == "apache,apache-2.0,mit"
    flat = " " + " ".join(re.findall(r"[0-9a-z]+", text)) + " "
    for d in r["detections"][:: n // 7]:
        assert flat[d["start"] : d["end"]] in ("licensed under the apache license", "apache license version 2 0", "mit license", "licensed under the apache license version 2 0")


def shortest(pattern):
    """A text that the pattern matches, without what is optional."""
    out = ""
    for op, x in pattern:
        match str(op):
            case "LITERAL":
                out += chr(x)
            case "IN":
                out += chr(x[0][1])
            case "ANY":
                out += "x"
            case "BRANCH":
                out += shortest(x[1][0])
            case "SUBPATTERN":
                out += shortest(x[3])
            case "MAX_REPEAT" | "MIN_REPEAT":
                out += x[0] * shortest(x[2])
    return out


def test_license_gates_let_every_rule_match(spark):
    every = license_scan.rules()
    texts = [shortest(re._parser.parse(r.pattern)) for r in every]
    for r, text in zip(every, texts):
        assert re.fullmatch(r.pattern, text) and r.keyword in text, r
    headers = [(k, f"// {t}", r.label) for k, (r, t) in enumerate(zip(every, texts)) if "spdx" in r.pattern]
    headers += [(9001, "SPDX-License-Identifier: MIT", "mit"), (9002, "SPDX-License-Identifier: MPL-2.0", "mpl-2.0"), (9003, "SPDX-License-Identifier: BSD-3-Clause", "bsd-3-clause")]
    got = {r["id"]: r["labels"] for r in license_scan.scan_licenses(table(spark, [(k, t, "en", "a") for k, t, _ in headers])).collect()}
    for k, text, label in headers:
        assert label in got[k].split(","), (text, got[k])


@pytest.mark.parametrize("name", sorted(queries()))
def test_queries_cover_the_table(spark, name):
    found = queries()[name](spark, SF)
    rows = found.collect()
    n = spark.read.parquet(f"{SF}/documents.parquet").count()
    assert len(rows) == n if name not in ("op9_neighbour_packing", "pipeline") else len({r["doc_id"] for r in rows}) <= n
    assert not any(kind in ("array", "map", "struct") for _, kind in found.dtypes)


def test_forget_frees_the_encoders():
    path = P.path("word_bpe_49k.json")
    first = encoder(path, "word_level")
    ids = first.encode(["Some words, some more."])
    forget()
    again = encoder(path, "word_level")
    assert again is not first and not again.cache and again.encode(["Some words, some more."]) == ids


def test_words_are_cut_as_the_split_pattern_does():
    """Apostrophes, single numbers, white space of Latin-1, and ends of texts, many texts at once."""
    rnd = random.Random(4)
    letters = "ab'strevmld .!?9²\xa0é\x85ÀßÿªµI\n''\x1c"
    for _ in range(3000):
        texts = ["".join(rnd.choice(letters) for _ in range(rnd.randint(0, 14))) for _ in range(rnd.randint(1, 4))]
        data = "".join(texts).lower().encode("latin-1")
        start, end = tokenise.word_cuts(data, np.append(0, np.cumsum([len(x) for x in texts])))
        assert [data[a:b].decode("latin-1") for a, b in zip(start, end)] == [w for x in texts for w in tokenise._SPLIT["word_level"].findall(x.lower())]


def test_a_distinct_word_of_a_batch_is_looked_up_once():
    """The cache is asked for each distinct piece of the texts, and their ids are the library's."""
    path = P.path("word_bpe_49k.json")
    tok, asked = Encoder(path, "word_level"), []

    class Watched(dict):
        def get(self, key, *rest):
            asked.append(key)
            return super().get(key, *rest)

    tok.cache = Watched()
    texts = ["Don't go, don't: naïve Ünïts 42 of THE the\xa0the", "", "the café's 'street' ÿª", "日本 the", "<|endoftext|> the"]
    library = Tokenizer.from_file(path)
    for _ in range(2):
        asked.clear()
        assert [np.frombuffer(x, "<u4").tolist() for x in tok.encode(texts)] == [library.encode(x, add_special_tokens=False).ids for x in texts]
        assert len(asked) == len(set(asked)) > 10


def test_words_are_merged_without_the_library():
    """New words of up to WIDE bytes are merged here, many at once, as the library does; longer ones go to it; the cache starts anew when full."""
    path, rnd = P.path("word_bpe_49k.json"), random.Random(9)
    parts = ["the", "in", "tion", "er", "sch", "é", "ß", "ou", "aa", "aaa", "z", "ij", "anthro", "ß"]
    words = sorted({"".join(rnd.choices(parts, k=rnd.randint(1, 9))) for _ in range(6000)} | {"=" * k for k in range(1, 70)} | {"é" * k for k in range(1, 40)} | {"a" * k for k in range(1, 70)})
    library, tok = Tokenizer.from_file(path), Encoder(path, "word_level", 2000)
    sent = []
    tok.library = type("Watched", (), {"encode_batch_fast": lambda _, texts, **k: (sent.extend(texts), library.encode_batch_fast(texts, **k))[1]})()
    for k in range(0, len(words), 500):
        texts = [" ".join(words[i : i + 10]) for i in range(k, min(k + 500, len(words)), 10)]
        assert [np.frombuffer(x, "<u4").tolist() for x in tok.encode(texts)] == [library.encode(x, add_special_tokens=False).ids for x in texts]
        assert len(tok.cache) <= 2500
    assert set(sent) == {x for x in words if len(x.encode()) > tokenise.WIDE}
    assert Encoder(path, "word_level").most == tokenise.CACHE_WORDS < tokenise.CACHE_PIECES


def test_few_neighbours_are_put_in_order_first(monkeypatch):
    """Best first and ties by place, whatever is put in order at first, and the same with keys of half the width."""
    rnd = np.random.default_rng(8)
    score = rnd.integers(0, 40, 500) / 8
    want = [k for k in np.argsort(-score, kind="stable").tolist() if score[k] > 0]
    assert list(packing.best_first(score)) == want and list(packing.best_first(np.zeros(3))) == []
    monkeypatch.setattr(packing, "FEW", 1)
    assert list(packing.best_first(score)) == want
    docs = [rnd.integers(0, 1 << 16, rnd.integers(1, 50)).astype("<u2") for _ in range(70)]
    for few, many in zip(packing.counted(docs), packing.counted([d.astype("<u4") for d in docs])):
        assert few.dtype == many.dtype and few.tolist() == many.tolist()


def test_common_terms_are_scored_by_rows(monkeypatch):
    """Rows for the terms of many documents give what postings alone give, also when documents have been used."""
    rnd = np.random.default_rng(3)
    docs = [np.minimum(rnd.zipf(1.3, rnd.integers(1, 80)), 500).astype(np.uint32) for _ in range(120)]
    index = packing.Index(docs, packing.PackSpec())
    assert len(index.live[3]) > 5 and (index.held * packing.DENSE >= index.n).sum() == len(index.live[3])
    monkeypatch.setattr(packing, "DENSE", 0)
    plain = packing.Index(docs, packing.PackSpec())
    assert len(plain.live[3]) == 0
    unused = np.ones(len(docs), bool)
    for seed in rnd.permutation(len(docs)):
        unused[seed] = False
        assert index.neighbours(seed, unused).tolist() == plain.neighbours(seed, unused).tolist()


@pytest.mark.parametrize("most", [0, 500_000])
def test_components_of_few_links_take_no_rounds(spark, monkeypatch, most):
    """The same components by rounds and in the driver, there with two tables written; none without links."""
    rnd = random.Random(8)
    links = [(rnd.randint(0, 90), rnd.randint(0, 90)) for _ in range(40)] + [(2**60 - k, 2**60 - k - 1) for k in range(9)]
    root = {x: x for link in links for x in link}
    for _ in root:
        for a, b in links:
            root[a] = root[b] = min(root[a], root[b])
    monkeypatch.setattr("histreplay.llm.components.LOCAL_LINKS", most)
    since = common.written()
    found = components(spark.createDataFrame(links, "a long, b long"))
    assert most == 0 or common.written() - since == 2
    assert {r["id"]: r["root"] for r in found.collect()} == {x: root[x] for a, b in links if a != b for x in (a, b)}
    if most:
        assert components(spark.createDataFrame([], "a long, b long")).count() == 0
