"""Jump consistent hashing of documents to shards, in SQL expressions alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from histreplay.llm.common import bucket_of, range_bounds, shuffle_width, stored, unused, with_prefix_sums

#: Jumps looked at where there are more shards than this. A key makes about ln(shards) jumps; 256 of them have a chance under 1e-200.
MOST_JUMPS = 256


def jump_shard(key: Column, shards: int) -> Column:
    """The shard of a string key. Jump k goes from shard b to floor((b + 1) / u_k), u_k in (0, 1] drawn from key and k;

    the last place before `shards` counts. The draws don't depend on the number of shards, so that one more shard
    takes keys only into itself.
    """
    if shards < 1:
        raise ValueError("at least one shard is needed")
    if shards == 1:
        return F.lit(0)
    draw = lambda k: (F.conv(F.substring(F.md5(F.concat_ws(":", key, k.cast("string"))), 1, 8), 16, 10).cast("double") + 1.0) / float(1 << 32)
    steps = F.sequence(F.lit(1), F.lit(min(shards, MOST_JUMPS)))
    start = F.struct(F.lit(0.0).alias("b"), F.lit(0.0).alias("j"))

    def step(at: Column, k: Column) -> Column:
        place = F.when(at["j"] < shards, at["j"]).otherwise(at["b"])
        after = F.when(at["j"] < shards, F.floor((at["j"] + 1.0) / draw(k)).cast("double")).otherwise(at["j"])
        return F.struct(place.alias("b"), after.alias("j"))

    return F.aggregate(steps, start, step, lambda at: F.when(at["j"] < shards, at["j"]).otherwise(at["b"])).cast("int")


def shard_key(id_col: str, text_col: str) -> Column:
    """What decides a document's shard: its id, or the checksum of its text where the id is null."""
    crc = F.crc32(F.coalesce(F.col(text_col), F.lit("")).cast("binary"))
    return F.coalesce(F.col(id_col).cast("string"), F.concat(F.lit("crc"), crc.cast("string")))


def shard_documents(docs: DataFrame, shards: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, size, text_crc32, shard, slot, grown_shard), a row for each document.

    The id decides the shard (the text's checksum for null ids); grown_shard is the shard if there were one more.
    slot numbers a shard's rows from 0 without gaps, by id, then size and checksum. size is the text's UTF-8 bytes plus
    1; null texts have none. Repeated rows share a shard and have slots of their own. An empty table gives an empty
    result.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    crc = F.crc32(text.cast("binary"))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), (F.octet_length(text) + 1).cast("long").alias("size"), crc.alias("text_crc32"), shard_key(id_col, text_col).alias("key"))
    rows = rows.select("id", "size", "text_crc32", jump_shard(F.col("key"), shards).alias("shard"), jump_shard(F.col("key"), shards + 1).alias("grown_shard"), F.lit(1).cast("long").alias("one"))
    rows = stored(rows, "shards")
    bounds = range_bounds(rows, "id", shuffle_width(rows.sparkSession))
    placed = rows.withColumn("bucket", bucket_of(F.col("id"), bounds))
    order = [F.col("id").asc_nulls_first(), F.col("size"), F.col("text_crc32")]
    found = with_prefix_sums(placed, ["shard"], "bucket", order, {"one": "slot"})
    return found.select("id", "size", "text_crc32", "shard", "slot", "grown_shard")


def write_shards(docs: DataFrame, path: str, shards: int, id_col: str = "doc_id", text_col: str = "text") -> str:
    """Writes whole documents to path/shard=k/, in the shards of shard_documents; each task writes those of its own rows.

    No shuffle is needed. Returns the folder column's name: underscores follow it where documents have a column `shard`.
    """
    (name,) = unused(docs.columns, "shard")
    docs.withColumn(name, jump_shard(shard_key(id_col, text_col), shards)).write.partitionBy(name).parquet(path)
    return name
