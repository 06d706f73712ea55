"""Helpers that several operators share: shared scratch tables, ordered prefix sums, skew-safe joins."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable, Iterator, Sequence
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: A side with at most this many rows of a few scalar columns may be broadcast.
BROADCAST_ROWS = 1_000_000
#: A join key that holds at least this share of the rows counts as hot; there are at most 1 / share of them.
HOT_SHARE = 1 / 500
#: Rows of a batch to a Python worker.
ARROW_ROWS = 500
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"

_local_scratch: str | None = None
_written: list[str] = []


def scratch(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; where that is unset, a local one in local mode only."""
    global _local_scratch
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir is unset: the executors share no folder with the driver")
    if _local_scratch is None:
        _local_scratch = f"file://{tempfile.mkdtemp(prefix='histreplay-')}"
    return _local_scratch


@contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """Batches to Python workers hold ARROW_ROWS rows in what runs meanwhile, since a row may be a whole text or set."""
    former = spark.conf.get(_BATCH, None)
    spark.conf.set(_BATCH, str(ARROW_ROWS))
    try:
        yield
    finally:
        spark.conf.unset(_BATCH) if former is None else spark.conf.set(_BATCH, former)


def stored(df: DataFrame, tag: str) -> DataFrame:
    """Writes a table to the shared folder and reads it back: cuts lineage and fixes the rows for later passes."""
    spark = df.sparkSession
    path = f"{scratch(spark)}/{tag}-{uuid.uuid4().hex}"
    _written.append(path)
    with small_batches(spark):
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def written() -> int:
    """How many tables stored() has written in this process and release() has not deleted."""
    return len(_written)


def release(spark: SparkSession, since: int = 0, keep: int = 0) -> int:
    """Deletes the tables that stored() has written in this process, but for the first `since` and the last `keep`.

    For callers who have written their results.
    """
    gone = _written[since : len(_written) - keep]
    del _written[since : len(_written) - keep]
    for name in gone:
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    return len(gone)


def unused(columns: Sequence[str], *names: str) -> list[str]:
    """The names, each with as many underscores added as make it differ from all columns (in any case of letters)."""
    taken = {c.lower() for c in columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def ship(spark: SparkSession) -> None:
    """Lets Python workers on this machine import the package when only the driver's sys.path has it."""
    root = str(Path(__file__).resolve().parents[2])
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root not in paths:
        env["PYTHONPATH"] = os.pathsep.join([root, *paths])


def give_back() -> None:
    """Returns what this process has freed to the system; allocators keep it otherwise."""
    import ctypes
    import gc

    import pyarrow

    gc.collect()
    pyarrow.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def give_back_heaps(spark: SparkSession) -> None:
    """Has the executors collect their garbage, upon which their heaps shrink; they stay as large as they once were otherwise.

    For what comes between large stages. A task for each core reaches all executors if they are idle; which it meets decides no row.
    """
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.expr("java_method('java.lang.System', 'gc')")).collect()


def tidied(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """The function for mapInArrow; when its task ends, the Python worker gives freed memory back, since workers outlive their tasks."""

    def whole(batches: Iterator) -> Iterator:
        yield from run(batches)
        give_back()

    return whole


def shuffle_width(spark: SparkSession) -> int:
    return max(2, int(spark.conf.get("spark.sql.shuffle.partitions")))


def range_bounds(df: DataFrame, key: str, parts: int) -> list:
    """Cut points of about equal shares of the rows by one numeric column; at most parts - 1 scalars reach the driver."""
    if parts < 2:
        return []
    shares = [k / parts for k in range(1, parts)]
    row = df.agg(F.percentile_approx(key, shares, 100 * parts).alias("cuts")).first()
    return sorted(set(row["cuts"] or []))


def bucket_of(key: Column, bounds: Sequence) -> Column:
    """How many bounds lie below the key; found in two levels, so that many bounds stay cheap. A null key gets 0."""
    if not bounds:
        return F.lit(0)
    width = max(8, int(len(bounds) ** 0.5))
    groups = [list(bounds[k : k + width]) for k in range(0, len(bounds), width)]
    tops = F.array(*[F.lit(g[-1]) for g in groups])
    group = F.size(F.filter(tops, lambda top: top < key))
    inner = F.element_at(F.array(*[F.array(*[F.lit(x) for x in g]) for g in groups]), group + 1)
    full = F.lit(len(groups)) == group
    found = F.when(full, F.lit(len(bounds))).otherwise(group * width + F.size(F.filter(inner, lambda cut: cut < key)))
    return F.coalesce(F.when(key.isNotNull(), found), F.lit(0)).cast("int")


def with_prefix_sums(df: DataFrame, group: list[str], bucket: str, order: list[Column], sums: dict[str, str]) -> DataFrame:
    """Adds for each row the sums over all earlier rows of its group; sums maps a column to the name of its prefix sum.

    Rows are ordered by bucket, then by `order` (a total order up to equal rows). A task holds one bucket of one
    group; the totals of the buckets, a row each, are summed over in a second, small pass.
    """
    keys = [*group, bucket]
    inner = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    outer = Window.partitionBy(*(group or [F.lit(0)])).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    totals = df.groupBy(*keys).agg(*[F.sum(c).alias(f"__t_{c}") for c in sums])
    base = totals.select(
        *[F.col(k).alias(f"__k_{k}") for k in keys],
        *[F.coalesce(F.sum(f"__t_{c}").over(outer), F.lit(0)).alias(f"__b_{c}") for c in sums],
    )
    local = df.withColumns({f"__l_{c}": F.coalesce(F.sum(c).over(inner), F.lit(0)) for c in sums})
    same = None
    for k in keys:
        one = local[k].eqNullSafe(base[f"__k_{k}"])
        same = one if same is None else same & one
    return local.join(base, same).select(*df.columns, *[(F.col(f"__l_{c}") + F.col(f"__b_{c}")).alias(name) for c, name in sums.items()])


def join_groups(rows: DataFrame, groups: DataFrame, keys: list[str], weight: str, fixed: bool = False) -> DataFrame:
    """Left-joins rows with a table that has one row for each key; keys are not null, `weight` counts the key's rows.

    Hot keys (a share of HOT_SHARE or more, so at most 1 / HOT_SHARE of them) are broadcast, and their rows are dealt
    out at random in the shuffle join that serves the others, at every size. The cold side's salt is 0, written so that the optimiser
    can't fold it and drop it from the join's keys. Three passes read the groups, which are written first unless they are `fixed`:
    a written table already.
    """
    groups = groups if fixed else stored(groups, "groups")
    total = groups.agg(F.sum(weight)).first()[0] or 0
    value_cols = [c for c in groups.columns if c not in keys]
    least = max(2, int(total * HOT_SHARE))
    hot = groups.filter(F.col(weight) >= least).select(*keys, F.struct(*value_cols).alias("__hot"))
    cold = groups.filter(F.col(weight) < least).select(*keys, F.struct(*value_cols).alias("__cold"), F.least(F.col(weight), F.lit(0)).cast("int").alias("__salt"))
    marked = rows.join(F.broadcast(hot), keys, "left")
    salt = F.when(F.col("__hot").isNull(), 0).otherwise(1 + F.pmod(F.xxhash64(*rows.columns), F.lit(1_000_000)))
    joined = marked.withColumn("__salt", salt.cast("int")).join(cold.hint("shuffle_merge"), [*keys, "__salt"], "left")
    found = F.coalesce("__hot", "__cold")
    return joined.select(*rows.columns, *[found[c].alias(c) for c in value_cols])


def by_ids(docs: DataFrame, ids: DataFrame, keys: list[str], how: str) -> DataFrame:
    """Semi or anti join of whole documents with a table of keys, which is broadcast only if it is counted small."""
    if ids.count() <= BROADCAST_ROWS:
        ids = F.broadcast(ids)
    same = None
    for k in keys:
        one = docs[k].eqNullSafe(ids[k])
        same = one if same is None else same & one
    return docs.join(ids, same, how)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
