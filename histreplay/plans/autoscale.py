"""Elastic scaling of preprocessing workers by starvation of accelerators and waste of workers."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.schema import HOUR


@dataclass(frozen=True)
class Policy:
    starving: float = 0.05
    wasting: float = 0.3
    gain: float = 0.5
    least: int = 1
    most: int = 1000


def step(workers: int, starvation: float, waste: float, policy: Policy = Policy()) -> int:
    """More workers while accelerators starve, fewer while workers idle, else as many."""
    if starvation > policy.starving:
        workers = math.ceil(workers * (1 + policy.gain * starvation))
    elif waste > policy.wasting:
        workers = math.floor(workers * (1 - policy.gain * waste))
    return min(policy.most, max(policy.least, workers))


def simulate(signals: DataFrame, start: int, policy: Policy = Policy()) -> DataFrame:
    """(tick, workers) for signals (tick, starvation, waste) of one job, whose ticks fit in one row; jobs go side by side."""
    job = "job" if "job" in signals.columns else None
    keyed = signals if job else signals.withColumn("job", F.lit(0))
    series = keyed.groupBy("job").agg(F.sort_array(F.collect_list(F.struct("tick", "starvation", "waste"))).alias("s"))
    first = F.struct(F.lit(start).alias("w"), F.array().cast("array<struct<tick:bigint,workers:int>>").alias("out"))

    def fold(state, x):
        up = F.ceil(state["w"] * (1 + policy.gain * x["starvation"]))
        down = F.floor(state["w"] * (1 - policy.gain * x["waste"]))
        w = F.when(x["starvation"] > policy.starving, up).when(x["waste"] > policy.wasting, down).otherwise(state["w"])
        w = F.least(F.lit(policy.most), F.greatest(F.lit(policy.least), w)).cast("int")
        return F.struct(w.alias("w"), F.array_append(state["out"], F.struct(x["tick"].cast("bigint").alias("tick"), w.alias("workers"))).alias("out"))

    rows = series.select("job", F.inline(F.aggregate("s", first, fold, lambda s: s["out"])))
    return rows if job else rows.drop("job")


def signals(events: DataFrame, width: int = HOUR) -> DataFrame:
    """(job, tick, starvation, waste) of events with event_type and us: a job for each type, a tick for each `width` of time.

    A job has capacity for its mean load. What its accelerators lack of a busier tick's load is starvation, as a share of
    that load; what its workers have over in a quieter tick is waste, as a share of the capacity.
    """
    loads = events.filter("us is not null").groupBy(F.coalesce("event_type", F.lit("-")).alias("job"), F.floor(F.col("us") / width).alias("slot")).agg(F.count("*").alias("n"))
    span = loads.agg(F.min("slot").alias("lo"), F.max("slot").alias("hi"))
    jobs = loads.groupBy("job").agg(F.sum("n").alias("total")).crossJoin(F.broadcast(span))
    grid = jobs.select("job", "total", "lo", (F.col("hi") - F.col("lo") + 1).alias("ticks"), F.explode(F.sequence("lo", "hi")).alias("slot"))
    load, total = F.coalesce("n", F.lit(0)) * F.col("ticks"), F.col("total")
    series = grid.join(loads, ["job", "slot"], "left")
    return series.select("job", (F.col("slot") - F.col("lo")).alias("tick"), F.when(load > total, (load - total) / load).otherwise(0.0).alias("starvation"), F.when(load < total, (total - load) / total).otherwise(0.0).alias("waste"))
