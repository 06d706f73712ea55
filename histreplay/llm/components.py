"""Connected components of a table of links, by rounds of neighbour minima; every round is a written table."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.llm.common import join_groups, stored

#: Links, of two 64-bit ids each, that are joined in the driver's memory; more of them are joined by rounds over tables.
LOCAL_LINKS = 500_000


def joined(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The ids in links (a, b) and for each the smallest id reachable. Roots go under smaller roots until no link is left between two."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y, root = at[: len(a)], at[len(a) :], np.arange(len(ids))
    while len(x):
        p, q = root[x], root[y]
        np.minimum.at(root, np.maximum(p, q), np.minimum(p, q))
        while not np.array_equal(root, up := root[root]):
            root = up
        apart = root[x] != root[y]
        x, y = x[apart], y[apart]
    return ids, ids[root]


def components(links: DataFrame) -> DataFrame:
    """(a, b) links to (id, root): root is the smallest id reachable from id. Ids without a link are absent.

    Alternates two steps until the links are stars: each node hands its larger neighbours to its smallest neighbour,
    then each node hands its smaller ones to the smallest. The number of links never grows and the number of rounds
    is logarithmic in practice; a node's neighbours are never gathered in one row, only their minimum is, and the links
    of a node with very many are dealt over all tasks. Up to LOCAL_LINKS links are joined in the driver instead, where
    a round's many small jobs would take longer.
    """
    spark = links.sparkSession
    links = stored(links.filter("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct(), "links")
    if links.count() <= LOCAL_LINKS:
        own = links.toArrow()
        ids, roots = joined(*(own.column(k).to_numpy().astype(np.int64) for k in ("hi", "lo")))
        return stored(spark.createDataFrame(pa.table({"id": pa.array(ids, pa.int64()), "root": pa.array(roots, pa.int64())}), "id long, root long"), "roots")
    while True:
        both = links.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(links.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = stored(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count("*").alias("n")), "least")
        large = _handed(both.filter("v > u"), least)
        large = stored(large, "links")
        least = stored(large.groupBy(F.col("hi").alias("u")).agg(F.min("lo").alias("m"), F.count("*").alias("n")), "least")
        small = large.select(F.col("hi").alias("u"), F.col("lo").alias("v"))
        small = stored(_handed(small, least).union(least.select(F.col("u").alias("hi"), F.col("m").alias("lo"))).distinct(), "links")
        parents, children = small.select(F.col("hi").alias("id")), small.select(F.col("lo").alias("id")).distinct()
        deep = parents.join(children, "id", "left_semi").limit(1).count()
        several = small.groupBy("hi").count().filter("count > 1").limit(1).count()
        links = small
        if not deep and not several:
            roots = links.select(F.col("lo").alias("id"), F.col("lo").alias("root")).distinct()
            return links.select(F.col("hi").alias("id"), F.col("lo").alias("root")).union(roots)


def _handed(pairs: DataFrame, least: DataFrame) -> DataFrame:
    """Links from v to the smallest neighbour of u for each pair (u, v)."""
    return join_groups(pairs, least, ["u"], "n", fixed=True).filter("v <> m").select(F.greatest("v", "m").alias("hi"), F.least("v", "m").alias("lo")).distinct()
