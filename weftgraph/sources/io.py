"""Reading and writing graphs: edge lists in Spark's formats, adjacency text, partitioned and bucketed tables."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .graphs import Graph, from_adjacency, normalize

EDGE_SCHEMA = "src long, dst long"


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the folder the cluster names. Where the session names none, a local one gets a folder of its own, any other an error."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        path = sc.getConf().get("spark.checkpoint.dir")
        if not path and not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(path or tempfile.mkdtemp(prefix="checkpoints-"))


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path in the folder that driver and executors share."""
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"


def write_edges(edges: DataFrame, path: str, kind: str = "parquet") -> None:
    """csv, json, orc, parquet, or text with one "src dst" per line."""
    rows = edges.select("src", "dst")
    if kind == "text":
        rows = rows.select(F.concat_ws(" ", "src", "dst").alias("value"))
    rows.write.format(kind).save(path)


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", comment: str = "#") -> DataFrame:
    """Schemas are given, never inferred; lines of text that start with ``comment`` are skipped."""
    if kind != "text":
        return normalize(spark.read.schema(EDGE_SCHEMA).format(kind).load(path))
    parts = F.split(F.trim("value"), r"\s+")
    lines = spark.read.text(path).where(~F.startswith("value", F.lit(comment)) & (F.length(F.trim("value")) > 0))
    return normalize(lines.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst")))


def write_adjacency_text(g: Graph, path: str) -> None:
    """A line per vertex: its id and its neighbours."""
    g.adjacency().select(F.concat_ws(" ", F.col("id").cast("string"), F.array_join(F.col("nbrs_n").cast("array<string>"), " ")).alias("value")).write.text(path)


def read_adjacency_text(spark: SparkSession, path: str) -> Graph:
    parts = F.split(F.trim("value"), r"\s+").cast("array<long>")
    return from_adjacency(spark.read.text(path).select(parts[0].alias("id"), F.slice(parts, 2, F.size(parts)).alias("nbrs")))


def write_partitioned(edges: DataFrame, path: str, buckets: int) -> None:
    """Parquet with a folder per class of the source id, for partition pruning."""
    edges.withColumn("bucket", F.col("src") % buckets).repartition("bucket").write.partitionBy("bucket").parquet(path)


def save_bucketed(g: Graph, name: str, buckets: int) -> None:
    """The neighbour table bucketed and sorted by id: lookups join it without a shuffle of its side."""
    g.adjacency().write.bucketBy(buckets, "id").sortBy("id").mode("overwrite").saveAsTable(name)


def load_bucketed(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name)
