"""Joins that Spark has no operator for: as of a time, and by ranges in buckets of time."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, value: str) -> DataFrame:
    """Each left row with `value` of the latest right row of its key at or before its time; null if there is none.

    Both sides are laid on one time line and the last value is carried along: one shuffle by key and no join.
    """
    cols = left.columns
    a = left.select(F.col(key).alias("__k"), F.col(left_time).alias("__t"), F.lit(1).alias("__side"), F.struct(*cols).alias("__row"))
    b = right.select(F.col(key).alias("__k"), F.col(right_time).alias("__t"), F.lit(0).alias("__side"), F.col(value).alias("__v"))
    line = Window.partitionBy("__k").orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True).withColumn("__last", F.last("__v", ignorenulls=True).over(line))
    return both.filter("__side = 1").select("__row.*", F.col("__last").alias(value))


def in_range(left: DataFrame, right: DataFrame, key: str, time: str, lo: str, hi: str, width: int) -> DataFrame:
    """Rows of right whose time lies in [lo, hi] of a left row of the same key.

    Left rows are spread over the buckets of time that they touch, so a key with a long history doesn't meet all of it.
    """
    spread = left.withColumn("__b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    placed = right.withColumn("__b", F.floor(F.col(time) / width))
    return spread.join(placed, [key, "__b"]).filter((F.col(time) >= F.col(lo)) & (F.col(time) <= F.col(hi))).drop("__b")


def overlapping(left: DataFrame, right: DataFrame, keys: list[str], own: tuple[str, str], other: tuple[str, str], width: int) -> DataFrame:
    """Pairs of rows of the same keys whose intervals `own` of left and `other` of right overlap, ends included.

    Both sides are spread over the buckets of time that they touch, and a pair counts in the first bucket that both
    have; so a short interval doesn't meet all of a long history.
    """
    at = lambda c: F.floor(F.col(c) / width)
    a = left.withColumn("__b", F.explode(F.sequence(at(own[0]), at(own[1]))))
    b = right.withColumn("__b", F.explode(F.sequence(at(other[0]), at(other[1]))))
    meet = (F.col(own[0]) <= F.col(other[1])) & (F.col(own[1]) >= F.col(other[0])) & (F.col("__b") == F.greatest(at(own[0]), at(other[0])))
    return a.join(b, [*keys, "__b"]).filter(meet).drop("__b")


def salted(left: DataFrame, right: DataFrame, key: str, salts: int, how: str = "inner") -> DataFrame:
    """An equi-join whose hot keys are dealt over `salts` tasks; right is repeated so many times. how: inner, left, left_semi or left_anti."""
    a = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    b = right.withColumn("__salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return a.join(b, [key, "__salt"], how).drop("__salt")
