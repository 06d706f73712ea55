"""Model quality measures: normalised entropy and relative gains."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EPS = 1e-6


def clipped(p: Column) -> Column:
    return F.greatest(F.lit(EPS), F.least(F.lit(1 - EPS), p))


def log_loss(y: Column, p: Column) -> Column:
    return -F.when(y == 1, F.ln(p)).otherwise(F.ln(1 - p))


def ne(scored: DataFrame, keys: list[str], y: str = "label", p: str = "p") -> DataFrame:
    """(keys, ne): mean log loss over the entropy of the base rate, for each group of keys."""
    q = F.avg(F.col(y).cast("double"))
    entropy = -(q * F.ln(q) + (1 - q) * F.ln(1 - q))
    return scored.groupBy(*keys).agg((F.avg(log_loss(F.col(y), F.col(p))) / entropy).alias("ne"))


def ne_gain(reference: float, found: float) -> float:
    return (reference - found) / reference


def rate(purchases: Column, n: Column, base: Column, prior: float = 20.0) -> Column:
    """A smoothed rate of purchases among the latest events, drawn to the base rate."""
    return clipped((purchases + prior * base) / (n + prior))


def ab(users: DataFrame, arm: str, metrics: dict[str, Column]) -> DataFrame:
    """(metric, gain): treatment over control, minus 1, of each metric's mean over users. arm is 1 for treatment."""
    sums = users.agg(*[F.avg(F.when(F.col(arm) == k, m)).alias(f"{name}_{k}") for name, m in metrics.items() for k in (0, 1)])
    rows = F.array(*[F.struct(F.lit(name).alias("metric"), (F.col(f"{name}_1") / F.col(f"{name}_0") - 1).alias("gain")) for name in metrics])
    return sums.select(F.inline(rows))
