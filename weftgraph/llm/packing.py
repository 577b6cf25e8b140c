"""Best-fit packing of documents into bins under conflicts.

A bin carries a bitmap of its duplicate clusters and ``quota`` bitmaps of its sources. A piece may not enter a bin that
holds its cluster already, or its source ``quota`` times. Bins are kept in order of what they have left: the search
starts at the smallest residual that still holds the piece and goes on to its successors until a bin has no
conflict, which is the tightest compatible bin; with none, a bin is opened. Pieces come largest first.

Texts longer than a bin are cut into pieces; full pieces fill a bin each. The other pieces are dealt by hash into
blocks of about ``block_rows``, packed apart from each other, so a block's work and memory are bounded and no state is
shared. Sizes are numbers of words (runs without ASCII white space).

Null and blank texts have one piece of size 0. Null sources conflict with each other like a source of their own.
Equal rows are equal clusters and so never share a bin. No rows give no rows. Other columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_left, insort

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shipping import ship
from .common import read


def pack(sizes, sources, clusters, capacity: int, quota: int = 2) -> tuple[list[int], list[int]]:
    """(bin, offset) of each item, for items in the order given, largest first."""
    left: list[tuple[int, int]] = []
    held: list[int] = []
    planes: list[list[int]] = []
    used: list[int] = []
    bins, offsets = [], []
    source_bit = {s: 1 << i for i, s in enumerate(dict.fromkeys(sources))}
    cluster_bit = {c: 1 << i for i, c in enumerate(dict.fromkeys(clusters))}
    for size, source, cluster in zip(sizes, sources, clusters, strict=True):
        s, c = source_bit[source], cluster_bit[cluster]
        i = bisect_left(left, (size, -1))
        while i < len(left) and (held[left[i][1]] & c or planes[left[i][1]][-1] & s):
            i += 1
        if i < len(left):
            room, b = left.pop(i)
        else:
            room, b = capacity, len(held)
            held.append(0)
            planes.append([0] * quota)
            used.append(0)
        held[b] |= c
        k = next(k for k in range(quota) if not planes[b][k] & s)
        planes[b][k] |= s
        bins.append(b)
        offsets.append(used[b])
        used[b] += size
        insort(left, (room - size, b))
    return bins, offsets


def best_fit(df: DataFrame, capacity: int = 2048, quota: int = 2, block_rows: int = 4096, id_column: str = "doc_id", text: str = "text", source: str = "source", cluster: str | None = None) -> DataFrame:
    """One row per piece: id, piece, n_words, bin_id, start (where in the bin), capacity.

    cluster: column of duplicate clusters, such as near-duplicate components; equal texts are clusters if not given.
    """
    words = F.regexp_count(F.coalesce(F.col(text).cast("string"), F.lit("")), F.lit("[^\\x20\\x09-\\x0D]+")).cast("long")
    rows = df.select(F.col(id_column).alias("_id"), F.col(source).cast("string").alias("_source"), (F.xxhash64(F.coalesce(F.col(text).cast("string"), F.lit(""))) if cluster is None else F.xxhash64(F.col(cluster).cast("string"))).alias("_cluster"), words.alias("_words"))
    full = (F.col("_words") / capacity).cast("long")
    pieces = rows.select("*", F.explode(F.sequence(F.lit(0), F.when(F.col("_words") == 0, 0).otherwise(F.ceil(F.col("_words") / capacity) - 1).cast("int"))).alias("_piece"))
    pieces = pieces.withColumn("_size", F.when(F.col("_piece") < full, F.lit(capacity)).otherwise(F.col("_words") - full * capacity).cast("int"))
    whole = pieces.where(F.col("_size") == capacity)
    rest = pieces.where(F.col("_size") < capacity)
    blocks = max(1, -(-df.count() // block_rows))
    rest = rest.withColumn("_block", F.pmod(F.xxhash64("_id", "_cluster", "_piece"), F.lit(blocks)).cast("int"))
    kind = rows.schema["_id"].dataType.simpleString()

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.iloc[np.lexsort((pdf["_cluster"], pdf["_id"].fillna(-1), pdf["_id"].isna(), -pdf["_size"]))]
        bins, offsets = pack(pdf["_size"].tolist(), pdf["_source"].tolist(), pdf["_cluster"].tolist(), capacity, quota)
        block = pdf["_block"].iloc[0]
        return pd.DataFrame({"_id": pdf["_id"].to_numpy(), "_piece": pdf["_piece"].to_numpy(), "_size": pdf["_size"].to_numpy(), "bin_id": [f"b{block}-{b}" for b in bins], "start": offsets})

    ship(df.sparkSession)
    packed = rest.select("_id", "_source", "_cluster", "_piece", "_size", "_block").groupBy("_block").applyInPandas(run, f"_id {kind}, _piece int, _size int, bin_id string, start int")
    alone = whole.select("_id", "_piece", "_size", F.concat_ws("-", F.lit("f"), F.col("_id").cast("string"), F.hex("_cluster"), F.col("_piece").cast("string")).alias("bin_id"), F.lit(0).alias("start"))
    return packed.unionByName(alone).select(F.col("_id").alias(id_column), F.col("_piece").alias("piece"), F.col("_size").alias("n_words"), "bin_id", "start", F.lit(capacity).alias("capacity"))


def packing_report(packed: DataFrame) -> DataFrame:
    """One row: bins, words, and the share of all bins' room that is filled."""
    return packed.groupBy("bin_id", "capacity").agg(F.sum("n_words").alias("w")).agg(F.count(F.lit(1)).alias("bins"), F.sum("w").alias("words"), (F.sum("w") / F.sum("capacity")).alias("filled"))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    return best_fit(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "source"))
