"""MinHash near-duplicate detection with tensored banding, and exact checks of all candidates."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.llm.common import BROADCAST_ROWS, by_ids, join_groups, release, ship, stored, tidied, written
from histreplay.llm.components import components
from histreplay.llm.textbytes import mix, shingle_sets, slices


@dataclass(frozen=True)
class NearDupSpec:
    """words: of a shingle. Documents link where percent_of_union of their union is shared.

    Two collections of `bands` bands of `rows` minhashes each: 2 * bands * rows hashes are computed, and a table key is
    made from each pair of a band of the first and a band of the second collection, so there are bands ** 2 tables of
    2 * rows hashes. At a similarity of 0.75 the default misses a pair with a chance of 3e-4.
    Buckets of up to `split` documents give all their pairs; larger ones are taken apart (see candidates). block_bytes
    of shingle sets, twice, are in a task's memory when a family of large buckets is searched.
    """

    words: int = 5
    percent_of_union: int = 75
    bands: int = 16
    rows: int = 3
    split: int = 8
    block_bytes: int = 4 << 20
    seed: int = 7


def _seeds(spec: NearDupSpec) -> tuple[np.ndarray, np.ndarray]:
    base = np.arange(1, 2 * spec.bands * spec.rows + 1, dtype=np.uint64)
    return mix(base + np.uint64(spec.seed << 20)), mix(base + np.uint64(spec.seed << 40)) | np.uint64(1)


def set_keys(sets: np.ndarray, starts: np.ndarray, spec: NearDupSpec) -> np.ndarray:
    """128 bits that name each shingle set, as two numbers."""
    return np.stack([np.add.reduceat(mix(sets), starts), np.bitwise_xor.reduceat(mix(sets ^ _seeds(spec)[0][0]), starts)], 1)


def sketch(docs: DataFrame, id_col: str, text_col: str, spec: NearDupSpec) -> DataFrame:
    """(id, n_shingles, set_key, a, b, mins): set_key names the exact shingle set, a and b hold the bands' hashes.

    mins has the low 16 bits of each minhash, for an estimate of the similarity. All four are null for an empty set.
    """
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        xor, mul = _seeds(spec)
        n_hash = len(xor)
        for batch in batches:
            out: list[list] = [[], [], [], [], []]
            for _, data, off in slices(batch.column(1)):
                sets, at = shingle_sets(data, off, spec.words)
                n = np.diff(at)
                full = np.flatnonzero(n)
                starts = at[:-1][full]
                mins = np.empty((len(full), n_hash), np.uint64)
                if len(full):
                    for k in range(n_hash):
                        mins[:, k] = np.minimum.reduceat((sets ^ xor[k]) * mul[k], starts)
                    keys = set_keys(sets, starts, spec)
                bands = np.zeros((len(full), 2 * spec.bands), np.uint64)
                for r in range(spec.rows):
                    bands = mix(bands + mins[:, r :: spec.rows])
                bands = mix(bands + np.arange(2 * spec.bands, dtype=np.uint64)).view(np.int64)
                low = mins.astype(np.uint16)
                row = {int(d): k for k, d in enumerate(full)}
                for d in range(len(n)):
                    k = row.get(d)
                    out[0].append(int(n[d]))
                    out[1].append(None if k is None else keys[k].tobytes())
                    out[2].append(None if k is None else bands[k, : spec.bands])
                    out[3].append(None if k is None else bands[k, spec.bands :])
                    out[4].append(None if k is None else low[k].tobytes())
            kinds = (pa.int64(), pa.binary(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(x, kind) for x, kind in zip(out, kinds)]], ["id", "n_shingles", "set_key", "a", "b", "mins"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(tidied(run), "id long, n_shingles long, set_key binary, a array<long>, b array<long>, mins binary")


def shingle_table(docs: DataFrame, id_col: str, text_col: str, spec: NearDupSpec) -> DataFrame:
    """(id, set_key, grams): the whole sorted shingle set of each document that has one, as 64-bit values, and its name."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, data, off in slices(batch.column(1)):
                sets, at = shingle_sets(data, off, spec.words)
                full = np.flatnonzero(np.diff(at))
                if len(full):
                    keys = set_keys(sets, at[:-1][full], spec)
                    own = [[x.tobytes() for x in keys], [sets[at[d] : at[d + 1]].tobytes() for d in full]]
                    yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(first + full)), *[pa.array(x, pa.binary()) for x in own]], ["id", "set_key", "grams"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(tidied(run), "id long, set_key binary, grams binary")


def buckets(reps: DataFrame, spec: NearDupSpec) -> tuple[DataFrame, DataFrame]:
    """(bucket, id) of each table key that two documents or more may share, and (bucket, n, lo, hi) of those that do.

    The keys of the second collection are spread only for documents whose band of the first has a partner.
    """
    first = reps.select("id", "b", F.explode("a").alias("band"))
    shared = first.groupBy("band").agg(F.count("*").alias("n")).filter("n > 1")
    half = join_groups(first, shared, ["band"], "n").filter("n is not null")
    members = half.select("id", F.explode("b").alias("other"), "band").select(F.xxhash64("band", "other").alias("bucket"), "id")
    members = stored(members, "members")
    groups = members.groupBy("bucket").agg(F.count("*").alias("n"), F.min("id").alias("lo"), F.max("id").alias("hi")).filter("n > 1")
    return members, stored(groups, "buckets")


def candidates(members: DataFrame, groups: DataFrame, spec: NearDupSpec) -> DataFrame:
    """Distinct pairs (a, b), a < b. A bucket of up to `split` documents gives all of its pairs.

    In a larger one each document pairs with the bucket's first and last. What that leaves open is found in
    family_links.
    """
    pairs = groups.filter("n = 2").select(F.col("lo").alias("a"), F.col("hi").alias("b")).distinct()
    kept = join_groups(members, groups.filter("n > 2"), ["bucket"], "n", fixed=True).filter("n is not null")
    few = kept.filter(F.col("n") <= spec.split).groupBy("bucket").agg(F.array_sort(F.collect_set("id")).alias("ids"))
    lists = few.filter("size(ids) > 1").select("ids").distinct()
    inside = lists.select(F.posexplode("ids").alias("k", "a"), "ids").select("a", F.explode(F.slice("ids", F.col("k") + 2, F.size("ids"))).alias("b"))
    big = kept.filter(F.col("n") > spec.split)
    stars = big.select(F.col("lo").alias("a"), F.col("id").alias("b")).union(big.select(F.col("id").alias("a"), F.col("hi").alias("b"))).filter("a < b")
    return pairs.union(inside).union(stars).distinct()


def _estimated(pairs: DataFrame, reps: DataFrame, spec: NearDupSpec) -> DataFrame:
    """Adds est, the share of equal minhashes, and drops pairs more than 4.5 standard errors under the threshold."""
    n_hash, goal = 2 * spec.bands * spec.rows, spec.percent_of_union / 100
    least = goal - 4.5 * (goal * (1 - goal) / n_hash) ** 0.5
    left, right = (reps.select(F.col("id").alias(k), F.col("mins").alias(f"mins_{k}"), F.col("n_shingles").alias(f"n_{k}")) for k in "ab")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            one, two = (np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint16).reshape(-1, n_hash) for k in (2, 3))
            est = (one == two).mean(1) if len(one) else np.zeros(0)
            keep = pa.array(est >= least)
            yield pa.RecordBatch.from_arrays([c.filter(keep) for c in (batch.column(0), batch.column(1), pa.array(est, pa.float64()))], ["a", "b", "est"])

    near = pairs.join(left, "a").join(right, "b").filter(100 * F.least("n_a", "n_b") >= spec.percent_of_union * F.greatest("n_a", "n_b"))
    return near.select("a", "b", "mins_a", "mins_b").mapInArrow(tidied(run), "a long, b long, est double")


def confirmed(pairs: DataFrame, sets: DataFrame, spec: NearDupSpec) -> DataFrame:
    """The pairs whose whole shingle sets meet the threshold."""
    share = spec.percent_of_union

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = np.zeros(batch.num_rows, bool)
            for k, (x, y) in enumerate(zip(batch.column(2), batch.column(3))):
                one, two = np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64)
                place = np.searchsorted(one, two)
                both = int((one[np.minimum(place, len(one) - 1)] == two).sum()) if len(one) and len(two) else 0
                keep[k] = both > 0 and 100 * both >= share * (len(one) + len(two) - both)
            mask = pa.array(keep)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(mask), batch.column(1).filter(mask)], ["a", "b"])

    left, right = (sets.select(F.col("id").alias(k), F.col("grams").alias(f"grams_{k}")) for k in "ab")
    return pairs.select("a", "b").join(left, "a").join(right, "b").select("a", "b", "grams_a", "grams_b").mapInArrow(tidied(run), "a long, b long")


def _between(pairs: DataFrame, roots: DataFrame) -> DataFrame:
    """The pairs whose ends aren't known to be in one component."""
    left, right = (roots.select(F.col("id").alias(k), F.col("root").alias(f"root_{k}")) for k in "ab")
    return pairs.join(left, "a", "left").join(right, "b", "left").filter(F.coalesce("root_a", "a") != F.coalesce("root_b", "b")).drop("root_a", "root_b")


def families(members: DataFrame, groups: DataFrame, roots: DataFrame, spec: NearDupSpec) -> DataFrame:
    """(id, family, root) of the documents in large buckets that still hold several components.

    Buckets that share a document are one family; a bucket that is one component already has no open pair.
    """
    big = groups.filter(F.col("n") > spec.split).select("bucket", "n")
    inside = join_groups(members, big, ["bucket"], "n", fixed=True).filter("n is not null").join(roots, "id", "left").withColumn("root", F.coalesce("root", "id"))
    inside = stored(inside.select("bucket", "n", "id", "root"), "inside")
    mixed = inside.groupBy("bucket").agg(F.min("root").alias("r0"), F.max("root").alias("r1"), F.min("id").alias("head"), F.max("n").alias("n")).filter("r0 <> r1")
    rest = join_groups(inside.select("bucket", "id", "root"), mixed.select("bucket", "head", "n"), ["bucket"], "n").filter("n is not null")
    rest = stored(rest.select("head", "id", "root").distinct(), "mixed")
    named = components(rest.select(F.col("head").alias("a"), F.col("id").alias("b")))
    return rest.select("id", "root").distinct().join(named.withColumnRenamed("root", "family"), "id")


def block_links(ids: np.ndarray, roots: np.ndarray, sets: list[np.ndarray], side: np.ndarray, share: int) -> list[tuple[int, int]]:
    """Links that join components, between documents of the two sides (within the one side if there is one).

    All documents outside the most common component are held against all of the other side, by counting shared
    shingles through an inverted index; so no pair between components is left out. Of the links found, those that
    join what isn't joined yet are returned.
    """
    parent: dict[int, int] = {int(r): int(r) for r in roots}

    def find(r: int) -> int:
        while parent[r] != r:
            parent[r] = parent[parent[r]]
            r = parent[r]
        return r

    lens = np.array([len(x) for x in sets], np.int64)
    flat = np.concatenate(sets)
    order = np.argsort(flat)
    flat = flat[order]
    new = np.concatenate([[True], flat[1:] != flat[:-1]])
    start = np.append(np.flatnonzero(new), len(flat))
    place = np.empty(len(flat), np.int32)
    place[order] = np.cumsum(new) - 1
    posted = np.repeat(np.arange(len(sets), dtype=np.int32), lens)[order]
    del flat, order, new
    ends = np.cumsum(lens)
    kinds, counts = np.unique(roots, return_counts=True)
    main, out = int(kinds[counts.argmax()]), []
    one = len(np.unique(side)) == 1
    for x in range(len(sets)):
        if find(int(roots[x])) == find(main):
            continue
        own = place[ends[x] - lens[x] : ends[x]]
        shared = np.bincount(np.concatenate([posted[start[t] : start[t + 1]] for t in own]), minlength=len(sets))
        hit = 100 * shared >= share * (lens[x] + lens - shared)
        hit[x] = False
        if not one:
            hit &= side != side[x]
        for y in np.flatnonzero(hit):
            a, b = find(int(roots[x])), find(int(roots[y]))
            if a != b:
                parent[max(a, b)] = min(a, b)
                out.append((int(ids[x]), int(ids[y])))
    return out


def family_links(kin: DataFrame, sets: DataFrame, spec: NearDupSpec) -> DataFrame:
    """(a, b) links between components of a family, from whole sets, in blocks of about spec.block_bytes of sets.

    A family's documents are dealt into blocks by a hash, and each pair of blocks is one group: the documents outside
    the main component are a query set against all rows of the family. No pairs are written out, only links.
    """
    sized = kin.join(sets, "id").withColumn("bytes", F.octet_length("grams"))
    sized = stored(sized, "kin")
    count = sized.groupBy("family").agg(F.ceil(F.sum("bytes") / spec.block_bytes).cast("int").alias("blocks"))
    dealt = sized.join(count, "family").withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    spread = dealt.select("family", "id", "root", "grams", "block", other)
    spread = spread.select("family", F.least("block", "other").alias("bi"), F.greatest("block", "other").alias("bj"), "block", "id", "root", "grams")

    def run(table: pa.Table) -> pa.Table:
        ids, roots, side = (table.column(k).to_numpy().astype(np.int64) for k in ("id", "root", "block"))
        sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in table.column("grams")]
        found = block_links(ids, roots, sets, side, spec.percent_of_union)
        return pa.table({"a": pa.array([x for x, _ in found], pa.int64()), "b": pa.array([y for _, y in found], pa.int64())})

    return spread.groupBy("family", "bi", "bj").applyInArrow(run, "a long, b long")


#: Nodes of sets whose id has other sets too are numbered from here.
_OTHER = 1 << 62


def _noded(rows: DataFrame, several: DataFrame | None) -> DataFrame:
    """Adds the node of each row with id and set_key: the id, or where the id has several sets, a hash of id and set."""
    if several is None:
        return rows.withColumn("node", F.col("id"))
    marks = several.select("id", F.lit(True).alias("many"))
    own = F.call_function("shiftrightunsigned", F.xxhash64("id", "set_key"), F.lit(2)).bitwiseOR(F.lit(_OTHER))
    joined = rows.join(F.broadcast(marks) if marks.count() <= BROADCAST_ROWS else marks, "id", "left")
    return joined.withColumn("node", F.when(F.col("many") & F.col("set_key").isNotNull(), own).otherwise(F.col("id"))).drop("many")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", spec: NearDupSpec = NearDupSpec()) -> DataFrame:
    """(id, n_shingles, component_id, kept), a row for each document.

    Documents with equal shingle sets are one class, of which the smallest id goes on; candidate pairs come from the
    tensored tables, and every link is confirmed on whole sets. Links are sought in three waves: each document with
    its most similar earlier candidate, then the pairs that still lie between components, then, exhaustively, large
    buckets that still hold several components.
    Null and empty texts have no shingle, link with nothing and are kept. Rows that repeat an id are one document with
    a text each: equal sets change nothing; different ones are searched each, and joined under the id (such ids must
    lie below 2^62). A null id is its own component (null) and kept. An empty table gives an empty result.
    """
    docs = docs.select(id_col, text_col)
    sketches = stored(sketch(docs, id_col, text_col, spec), "sketch")
    named = sketches.filter("set_key is not null and id is not null")
    mark = F.xxhash64("set_key")
    repeats = stored(named.groupBy("id").agg(F.count("*").alias("n"), F.min(mark).alias("x"), F.max(mark).alias("y")).filter("n > 1"), "repeats")
    repeated, several = repeats.limit(1).count() > 0, repeats.filter("x <> y").select("id")
    if not several.limit(1).count():
        several = None
    elif several.agg(F.max("id")).first()[0] >= _OTHER:
        raise ValueError("ids of 2^62 and more must not repeat with different texts")
    nodes = _noded(named, several)
    classes = nodes.groupBy("set_key").agg(F.min("node").alias("rep"), F.count("*").alias("n"))
    same = join_groups(nodes.select("node", "set_key"), classes.filter("n > 1"), ["set_key"], "n").filter("rep is not null")
    same = stored(same.filter("node <> rep").select("rep", "node").distinct(), "same")
    first = by_ids(nodes, same.select("node").distinct(), ["node"], "left_anti")
    first = first.dropDuplicates(["node"]) if repeated else first
    reps = stored(first.select(F.col("id").alias("doc"), F.col("node").alias("id"), "n_shingles", "a", "b", "mins"), "reps")

    def sets_of(wanted: DataFrame) -> DataFrame:
        """(id, grams) of the nodes in the one column of `wanted`."""
        if several is not None:
            wanted = reps.join(wanted.withColumnRenamed(wanted.columns[0], "id"), "id", "left_semi").select(F.col("doc").alias(id_col)).distinct()
        own = _noded(shingle_table(by_ids(docs, wanted, [id_col], "left_semi"), id_col, text_col, spec), several)
        return own.select(F.col("node").alias("id"), "grams")

    members, groups = buckets(reps, spec)
    pairs = stored(_estimated(candidates(members, groups, spec), reps, spec), "pairs")
    sets = stored(sets_of(pairs.select(F.col("a").alias(id_col)).union(pairs.select(F.col("b").alias(id_col))).distinct()), "sets")
    best = pairs.groupBy("b").agg(F.max_by("a", F.struct("est", "a")).alias("a")).select("a", "b")
    links = stored(confirmed(best, sets, spec), "linked")
    roots = components(links)
    more = stored(confirmed(_between(pairs, roots), sets, spec), "linked")
    links = links.union(more)
    if more.limit(1).count():
        roots = components(links)
    if groups.filter(F.col("n") > spec.split).limit(1).count():
        kin = families(members, groups, roots, spec)
        if kin.limit(1).count():
            links = links.union(stored(family_links(kin, sets_of(kin.select(F.col("id").alias(id_col))), spec), "linked"))
            roots = components(links)
    if same.limit(1).count() or several is not None:
        links = links.union(same.select(F.col("rep").alias("a"), F.col("node").alias("b")))
        if several is not None:
            links = links.union(nodes.filter("node <> id").select(F.col("id").alias("a"), F.col("node").alias("b")))
        roots = components(links)
    found = _noded(sketches.select("id", "set_key", "n_shingles"), several).join(roots.withColumnRenamed("id", "node"), "node", "left")
    root = F.coalesce("root", "id")
    return found.select("id", "n_shingles", root.alias("component_id"), root.eqNullSafe(F.col("id")).alias("kept"))


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", spec: NearDupSpec = NearDupSpec()) -> DataFrame:
    """The documents without those that belong to a component of a smaller id; all columns stay.

    What was written on the way is deleted; the list of ids that go stays.
    """
    since = written()
    found = near_duplicates(docs, id_col, text_col, spec)
    gone = stored(found.filter("not kept").select(F.col("id").alias(id_col)).distinct(), "gone")
    release(docs.sparkSession, since, keep=1)
    return by_ids(docs, gone, [id_col], "left_anti")
