"""Base batches for preprocessing workers and full batches for trainers; both are numbers on small rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def _numbered(df: DataFrame, order: list[Column], weight: Column | None = None) -> DataFrame:
    """Adds __n: rows (or weight) before each row in the given order, over all rows.

    Rows are first counted by coarse ranges of a 64-bit key, so that no task has to order them all.
    """
    own = weight if weight is not None else F.lit(1)
    keyed = df.withColumns({"__w": own.cast("long"), "__key": order[0]})
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cuts = keyed.agg(F.percentile_approx("__key", [k / parts for k in range(1, parts)], 10_000)).first()[0] if parts > 1 else []
    cuts = sorted(set(cuts or []))
    bounds = F.array(*[F.lit(c) for c in cuts]) if cuts else None
    placed = keyed.withColumn("__r", F.size(F.filter(bounds, lambda c: c < F.col("__key"))) if cuts else F.lit(0))
    inside = Window.partitionBy("__r").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    totals = placed.groupBy("__r").agg(F.sum("__w").alias("__t"))
    before = totals.select("__r", F.coalesce(F.sum("__t").over(Window.partitionBy(F.lit(0)).orderBy("__r").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__b"))
    local = placed.withColumn("__l", F.coalesce(F.sum("__w").over(inside), F.lit(0)))
    return local.join(F.broadcast(before), "__r").withColumn("__n", F.col("__l") + F.col("__b")).drop("__w", "__key", "__r", "__l", "__b")


def base(df: DataFrame, rows: int, id_col: str) -> DataFrame:
    """batch_id: `rows` consecutive rows by id."""
    return _numbered(df, [F.col(id_col)]).withColumn("batch_id", F.floor(F.col("__n") / rows)).drop("__n")


def clustered(df: DataFrame, rows: int, cluster: Column, id_col: str) -> DataFrame:
    """batch_id: `rows` consecutive rows in order of the cluster (a number), then by id."""
    return _numbered(df, [cluster, F.col(id_col)]).withColumn("batch_id", F.floor(F.col("__n") / rows)).drop("__n")


def base_by_bytes(df: DataFrame, budget: int, id_col: str, size_col: str) -> DataFrame:
    """batch_id by the bytes before a row, in steps of the budget: a batch holds at most the budget and one row more."""
    return _numbered(df, [F.col(id_col)], F.col(size_col)).withColumn("batch_id", F.floor(F.col("__n") / budget)).drop("__n")


def rebatch(batched: DataFrame, full_rows: int, seed: int, id_col: str) -> DataFrame:
    """full_id: rows merged and reshuffled into full batches, in the order of a hash of id and seed."""
    digest = F.md5(F.concat_ws(":", F.col(id_col).cast("string"), F.lit(str(seed))))
    keyed = batched.withColumns({"__d": digest, "__h": F.conv(F.substring(digest, 1, 13), 16, 10).cast("long")})
    return _numbered(keyed, [F.col("__h"), F.col("__d"), F.col(id_col)]).withColumn("full_id", F.floor(F.col("__n") / full_rows)).drop("__n", "__h", "__d")


def sweep(df: DataFrame, sizes: tuple[int, ...], id_col: str, elems_col: str) -> DataFrame:
    """(size, batches, peak_elems, mean_elems) for each base batch size: what a worker has to hold."""
    out = None
    for size in sizes:
        each = base(df, size, id_col).groupBy("batch_id").agg(F.sum(elems_col).alias("e"))
        own = each.agg(F.count("*").alias("batches"), F.max("e").alias("peak_elems"), F.avg("e").alias("mean_elems")).withColumn("size", F.lit(size))
        out = own if out is None else out.unionByName(own)
    return out
