"""Overlap of stripe lookups with primary reads."""

from __future__ import annotations

import queue
import threading
from collections.abc import Iterable, Iterator
from typing import TypeVar

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

T = TypeVar("T")


def makespan(batch_times: DataFrame, pipelined: bool = True) -> DataFrame:
    """(makespan) of batches (worker, batch_id, read_cost, lookup_cost): one after the other, or with the lookup of a

    batch over the read of the next. Workers run side by side; the longest counts, their sum is `work`.
    """
    after = F.lead("read_cost").over(Window.partitionBy("worker").orderBy("batch_id"))
    first = F.row_number().over(Window.partitionBy("worker").orderBy("batch_id")) == 1
    cost = F.col("read_cost") + F.col("lookup_cost")
    if pipelined:
        cost = F.when(first, F.col("read_cost")).otherwise(0) + F.greatest(F.col("lookup_cost"), F.coalesce(after, F.lit(0)))
    each = batch_times.withColumn("cost", cost).groupBy("worker").agg(F.sum("cost").alias("cost"))
    return each.agg(F.max("cost").alias("makespan"), F.sum("cost").alias("work"))


def ahead(items: Iterable[T], depth: int = 1) -> Iterator[T]:
    """The items in order, with up to `depth` of them made ahead in a thread; for use inside mapInArrow."""
    ready: queue.Queue = queue.Queue(maxsize=max(1, depth))
    end = object()

    def fill() -> None:
        try:
            for x in items:
                ready.put((x, None))
            ready.put((end, None))
        except BaseException as e:  # noqa: BLE001  raised again where the items are used
            ready.put((end, e))

    threading.Thread(target=fill, daemon=True).start()
    while True:
        x, error = ready.get()
        if x is end:
            if error is not None:
                raise error
            return
        yield x
