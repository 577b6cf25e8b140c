"""Connected components of a link table: on the driver where the links are few, else by star contraction."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

#: So many distinct links between longs at most (4 MB) may be joined on the driver, in three jobs instead of some four a round.
GATHERED = 1 << 18


def roots(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of the links (a, b) and for each the smallest one reachable."""
    nodes, flat = np.unique(np.concatenate((a, b)), return_inverse=True)
    a, b, root = flat[: len(a)], flat[len(a) :], np.arange(len(nodes))
    while (left := root[a] != root[b]).any():
        a, b = a[left], b[left]
        x, y = root[a], root[b]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (root[root] != root).any():
            root = root[root]
    return nodes, nodes[root]


def components(links: DataFrame, a: str = "a", b: str = "b", gathered: int = 0) -> DataFrame:
    """(node, component) of every node that has a link; component is the smallest node reachable.

    More than ``gathered`` links, or ends that are no longs, stay distributed: each round hangs every node's larger neighbours
    on its smallest one, then its smaller ones likewise; after a few rounds all trees are stars. Rows stay linear in the links.
    Null ends and loops are ignored.
    """
    pairs = links.select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).where(F.col("hi") > F.col("lo")).distinct()
    state = cut(pairs)
    if gathered and {kind for _, kind in state.dtypes} == {"bigint"} and state.count() <= gathered:
        own = state.toArrow()
        found = roots(own["hi"].to_numpy(), own["lo"].to_numpy())
        return state.sparkSession.createDataFrame(pa.table(dict(zip(("node", "component"), found, strict=True))), "node long, component long")
    while True:
        both = state.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(state.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = cut(both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct())
        small_least = large.groupBy(F.col("hi").alias("u")).agg(F.min("lo").alias("m"), F.count(F.lit(1)).alias("n"))
        tangled = small_least.where("n > 1").select(F.col("u").alias("hi"), "m")
        moved = large.join(tangled, "hi").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).where("hi > lo")
        nxt = cut(small_least.select(F.col("u").alias("hi"), F.col("m").alias("lo")).unionByName(moved).distinct())
        lows = nxt.select(F.col("lo").alias("hi")).distinct()
        if nxt.join(lows, "hi", "left_semi").isEmpty() and nxt.groupBy("hi").count().where("count > 1").isEmpty():
            return nxt.select(F.col("hi").alias("node"), F.col("lo").alias("component")).unionByName(lows.select(F.col("hi").alias("node"), F.col("hi").alias("component")))
        state = nxt
