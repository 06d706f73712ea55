"""Exact dedup by progressive refinement: byte length, then prefix hash, then the hash of the whole text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from histreplay.llm.common import BROADCAST_ROWS, join_groups, release, stored, unused, written

#: Characters that the second step hashes.
PREFIX = 256


def whole_hash(text: Column) -> Column:
    """SHA-256 of the UTF-8 bytes as lowercase hex; null counts as empty."""
    return F.sha2(F.coalesce(text, F.lit("")).cast("binary"), 256)


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hash_all: bool = False) -> DataFrame:
    """(id, keep_id, group_size, kept, full_hash, n_bytes, prefix), a row for each document.

    Step 1 groups by byte length; a length that occurs once settles its document. Step 2 groups the others by length
    and a hash of the first PREFIX characters. Step 3 hashes the whole text of what is left and groups by that. Text
    is never shuffled: where the groups left are few enough to broadcast, only their texts are read to the end, else
    all are. With hash_all every row gets its full_hash in the one scan, for callers who need it; otherwise rows
    settled earlier have null.

    The largest id of a group stays. Null texts equal empty ones. Rows that repeat an id and a text are one document
    listed twice: they count in group_size and share the decision. Null ids lose to others; in a group of null ids
    alone all are kept. An empty table gives an empty result.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    shape = [F.octet_length(text).alias("n_bytes"), F.xxhash64(F.left(text, F.lit(PREFIX))).alias("prefix")]
    digest = whole_hash(F.col(text_col)) if hash_all else F.lit(None).cast("string")
    rows = stored(docs.select(F.col(id_col).cast("long").alias("id"), *shape, digest.alias("full_hash")), "shape")
    lengths = rows.groupBy("n_bytes").agg(F.count("*").alias("n_len")).filter("n_len > 1")
    second = join_groups(rows, lengths, ["n_bytes"], "n_len").filter("n_len is not null").groupBy("n_bytes", "prefix").agg(F.count("*").alias("n_prefix"))
    open_keys = stored(second.filter("n_prefix > 1"), "open")
    if hash_all:
        third = join_groups(rows, open_keys, ["n_bytes", "prefix"], "n_prefix", fixed=True).filter("n_prefix is not null")
    else:
        source = docs.select(F.col(id_col).cast("long").alias("id"), *shape, text.alias("__text"))
        few = open_keys.count() <= BROADCAST_ROWS
        keys = F.broadcast(open_keys.drop("n_prefix"))
        if few:
            source = source.join(keys, ["n_bytes", "prefix"], "left_semi")
        third = stored(source.select("id", "n_bytes", "prefix", whole_hash(F.col("__text")).alias("full_hash")), "full")
        rows = third.unionByName(rows.join(keys, ["n_bytes", "prefix"], "left_anti")) if few else third
    groups = third.groupBy("full_hash").agg(F.max("id").alias("keep_id"), F.count("*").alias("group_size")).filter("group_size > 1")
    hashed = rows.filter("full_hash is not null")
    found = join_groups(hashed, groups, ["full_hash"], "group_size")
    if not hash_all:
        alone = rows.filter("full_hash is null").select("*", F.lit(None).cast("long").alias("keep_id"), F.lit(None).cast("long").alias("group_size"))
        found = found.unionByName(alone)
    keep = F.when(F.col("group_size").isNull(), F.col("id")).otherwise(F.col("keep_id"))
    return found.select("id", keep.alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"), keep.eqNullSafe(F.col("id")).alias("kept"), "full_hash", "n_bytes", "prefix")


def _matching(docs: DataFrame, found: DataFrame, id_col: str, text_col: str, how: str) -> DataFrame:
    """Semi or anti join of documents with rows (id, n_bytes, prefix, full_hash).

    Only texts whose id, length and prefix hash match are hashed to the end: the comparison of the whole hashes is
    written so that it is no key of the join. The rows are broadcast only if they are counted few.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    own = unused(docs.columns, "id", "n_bytes", "prefix")
    keyed = docs.withColumns(dict(zip(own, (F.col(id_col).cast("long"), F.octet_length(text), F.xxhash64(F.left(text, F.lit(PREFIX)))))))
    side = found.select(*[F.col(c).alias(f"{o}_of") for c, o in zip(("id", "n_bytes", "prefix"), own)], F.col("full_hash").alias(f"{own[2]}_hash"))
    side = F.broadcast(side) if found.count() <= BROADCAST_ROWS else side
    same = F.startswith(whole_hash(keyed[text_col]), side[f"{own[2]}_hash"])
    for o in own:
        same = keyed[o].eqNullSafe(side[f"{o}_of"]) & same
    return keyed.join(side, same, how)


def drop_exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each group of equal texts, that of the largest id; all columns stay. Rows that repeat id and text leave one row.

    Found by refinement: texts settled by their length or prefix are not hashed to the end. Which of the rows that
    repeat id and text stays, where other columns differ, is open.
    """
    since, shape = written(), ("id", "n_bytes", "prefix", "full_hash")
    found = stored(exact_duplicates(docs, id_col, text_col).filter("full_hash is not null"), "found")
    gone = stored(found.filter("not kept").select(*shape).distinct(), "gone")
    twice = stored(found.filter("kept").groupBy(*shape).agg(F.count("*").alias("n")).filter("n > 1").select(*shape), "twice")
    release(docs.sparkSession, since, keep=2)
    rest = _matching(docs, gone, id_col, text_col, "left_anti")
    if twice.limit(1).count():
        keys = unused(rest.columns, "hash")
        again = _matching(docs, twice, id_col, text_col, "left_semi").withColumn(keys[0], whole_hash(F.col(text_col)))
        again = again.dropDuplicates([id_col, *keys]).select(*docs.columns)
        rest = _matching(rest.select(*docs.columns), twice, id_col, text_col, "left_anti").select(*docs.columns).unionByName(again)
    return rest.select(*docs.columns)
