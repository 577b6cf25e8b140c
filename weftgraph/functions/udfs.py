"""Functions for use from SQL and DataFrames: pattern tables, and one of each kind of Python function.

The engine's own plans use none of them; they are for inspection and for users' glue.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans import schedules, symmetry
from ..plans.patterns import Pattern
from ..shipping import ship
from ..sources.graphs import Graph


@F.udf(T.LongType())
def edge_code(a: int, b: int) -> int | None:
    return None if a is None or b is None else min(a, b) * 1000003 + max(a, b)


@F.pandas_udf(T.LongType())
def edge_code_vectorized(a: pd.Series, b: pd.Series) -> pd.Series:
    return np.minimum(a, b) * 1000003 + np.maximum(a, b)


@F.pandas_udf(T.DoubleType())
def mean_of(x: pd.Series) -> float:
    return float(x.mean())


def higher_neighbours(adjacency: DataFrame) -> DataFrame:
    """id, higher: neighbours with a larger id, by Arrow batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists, ids = b.column("nbrs_n"), b.column("id").to_numpy()
            sizes = np.diff(np.asarray(lists.offsets))
            owner = np.repeat(np.arange(len(ids)), sizes)
            higher = np.bincount(owner[lists.flatten().to_numpy() > ids[owner]], minlength=len(ids))
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(higher, pa.int64())], ["id", "higher"])

    return adjacency.mapInArrow(run, "id long, higher long")


def local_triangles(g: Graph) -> DataFrame:
    """id, n: triangles at each vertex, counted in the vertex's own neighbourhood (grouped map)."""
    adj = g.adjacency()
    near = adj.select("id", F.explode("nbrs_n").alias("nbr")).join(adj.select(F.col("id").alias("nbr"), F.col("nbrs_n").alias("far")), "nbr")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own = set(pdf["nbr"])
        n = sum(len(own.intersection(x)) for x in pdf["far"]) // 2
        return pd.DataFrame({"id": [pdf["id"].iloc[0]], "n": [n]})

    return near.groupBy("id").applyInPandas(run, "id long, n long").where("n > 0")


class AutomorphismTable:
    def eval(self, pattern: str):
        p = Pattern.parse(pattern)
        for g in symmetry.automorphisms(p):
            yield list(g), ["".join(p.names[v] for v in s) for s in symmetry.swaps(g)]


class RestrictionTable:
    def eval(self, pattern: str):
        p = Pattern.parse(pattern)
        for i, s in enumerate(symmetry.restriction_sets(p)):
            for a, b in sorted(s):
                yield i, p.names[a], p.names[b]


class ScheduleTable:
    def eval(self, pattern: str):
        p = Pattern.parse(pattern)
        k = schedules.efficient(p)[1]
        for i, o in enumerate(schedules.all_orders(p)):
            one = schedules.is_connected_prefix(o, p)
            yield i, [p.names[v] for v in o], one, one and schedules.independent(o[p.n - k :], p)


def register(spark: SparkSession) -> None:
    """Pattern tables and edge functions under their SQL names."""
    ship(spark)
    spark.udtf.register("automorphisms", F.udtf(AutomorphismTable, returnType="perm array<int>, swaps array<string>"))
    spark.udtf.register("restriction_sets", F.udtf(RestrictionTable, returnType="set_id int, hi string, lo string"))
    spark.udtf.register("pattern_schedules", F.udtf(ScheduleTable, returnType="sched_id int, `order` array<string>, phase1 boolean, phase2 boolean"))
    spark.udf.register("edge_code", edge_code)
