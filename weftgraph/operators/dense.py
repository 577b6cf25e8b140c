"""Cliques of dense graphs by blocks of the adjacency matrix.

Vertices get dense numbers, cut into ranges of ``block``. The edges between two ranges are one block, kept as bits; a task gets the
blocks among k ranges and counts the cliques with one vertex in each of them, so no task holds more than k (k - 1) / 2 blocks.
A vertex of the first range narrows the others to its neighbours, until three ranges are left, which one matrix product counts.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from itertools import combinations, combinations_with_replacement

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.ids import dense_ids
from ..shipping import ship

#: Vertices of a block's side. Sums of products stay whole numbers that float32 holds.
BLOCK = 1024
#: Edges whose places a task gathers before it sends them.
EDGES_AT_ONCE = 1 << 20
#: Tasks a core that the choices of ranges are dealt to.
TASKS = 16
#: Under this sum of squared degrees lists are quick enough.
LEAST_SQUARES = 1 << 26
#: Multiplications of a product that cost as much as one member of a list looked up.
PRODUCTS_A_MEMBER = 150


def is_dense(g) -> bool:
    """Whether products over all vertices cost less than the lists of every edge's ends: n ** 3 against the squared degrees."""
    if g.directed or g.moments()[1] < LEAST_SQUARES:
        return False
    n = g.degrees().count()
    return n**3 < PRODUCTS_A_MEMBER * g.moments()[1]


def cliques(m: dict[tuple[int, int], np.ndarray], parts: tuple[int, ...]) -> int:
    """Cliques with one vertex in each part; m: float32 of 0 and 1 for each pair of parts."""
    if len(parts) == 2:
        return int(m[parts].sum(dtype=np.float64))
    if len(parts) == 3:
        a, b, c = parts
        return int(np.multiply(m[a, b] @ m[b, c], m[a, c]).sum(dtype=np.float64))
    first, rest, total = parts[0], parts[1:], 0
    for v in range(len(m[first, rest[0]])):
        near = {q: np.flatnonzero(m[first, q][v]) for q in rest}
        if all(len(x) for x in near.values()):
            total += cliques({(a, b): m[a, b][np.ix_(near[a], near[b])] for a, b in combinations(rest, 2)}, rest)
    return total


def packed(cells: np.ndarray, block: int) -> bytes:
    """The bits of a block with these cells set."""
    bits = np.zeros(block * block, bool)
    bits[cells] = True
    return zlib.compress(np.packbits(bits).tobytes(), 1)


def unpacked(data: bytes, block: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(zlib.decompress(data), np.uint8))[: block * block].reshape(block, block).astype(np.float32)


def blocks(g, block: int) -> DataFrame:
    """i, j, bits: the blocks that have edges, from the smaller to the larger vertex number."""

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Cells of the edges, block by block; a row for each block and some EDGES_AT_ONCE edges."""
        held: list[np.ndarray] = []

        def sent() -> pa.RecordBatch:
            e = np.concatenate(held)
            held.clear()
            e.sort(axis=1)
            where, cell = (e // block).astype(np.int64), (e[:, 0] % block) * block + e[:, 1] % block
            key = where[:, 0] << 32 | where[:, 1]
            at = np.argsort(key, kind="stable")
            keys, begins = np.unique(key[at], return_index=True)
            cells = [x.astype(np.int32).tobytes() for x in np.split(cell[at], begins[1:])]
            return pa.RecordBatch.from_arrays([pa.array((keys >> 32).astype(np.int32)), pa.array((keys & 0xFFFFFFFF).astype(np.int32)), pa.array(cells, pa.binary())], ["i", "j", "cells"])

        for b in batches:
            if len(b):
                held.append(np.column_stack([b.column("a").to_numpy(), b.column("b").to_numpy()]))
                if sum(map(len, held)) >= EDGES_AT_ONCE:
                    yield sent()
        if held:
            yield sent()

    def gathered(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        cells = np.concatenate([np.frombuffer(x, np.int32) for x in rows["cells"]])
        return pd.DataFrame({"i": [key[0]], "j": [key[1]], "bits": [packed(cells, block)]})

    ids = dense_ids(g.degrees(), "id", name="nth").select("id", "nth")
    e = g.edges.select("src", "dst").join(F.broadcast(ids.toDF("src", "a")), "src").join(F.broadcast(ids.toDF("dst", "b")), "dst").select("a", "b")
    return e.mapInArrow(places, "i int, j int, cells binary").groupBy("i", "j").applyInPandas(gathered, "i int, j int, bits binary")


def block_cliques(g, k: int, block: int = BLOCK) -> DataFrame:
    """One row, n: the k-cliques (k of 2 or more) of an undirected graph."""
    ship(g.spark)
    n = -(-g.degrees().count() // block) or 1
    every = [list(x) for x in combinations_with_replacement(range(n), k)]

    def counted(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        parts = [int(x) for x in key[0].split(",")]
        held = {(i, j): bits for i, j, bits in zip(rows["i"], rows["j"], rows["bits"], strict=True)}
        if any((parts[a], parts[b]) not in held for a, b in combinations(range(k), 2)):
            return pd.DataFrame({"n": [0]})
        made = {x: unpacked(held[x], block) for x in held}
        return pd.DataFrame({"n": [cliques({(a, b): made[parts[a], parts[b]] for a, b in combinations(range(k), 2)}, tuple(range(k)))]})

    # a block goes to each choice of k ranges, repeats allowed, that has both of its own (twice, if they are one)
    uses: dict[tuple[int, int], list[str]] = {}
    for x in every:
        for pair in set(combinations(x, 2)):
            uses.setdefault(pair, []).append(",".join(map(str, x)))
    at = g.spark.createDataFrame([(i, j, x) for (i, j), x in uses.items()], "i int, j int, parts array<string>")
    dealt = blocks(g, block).join(F.broadcast(at), ["i", "j"]).select("i", "j", "bits", F.explode("parts").alias("parts"))
    tasks = min(len(every), TASKS * g.spark.sparkContext.defaultParallelism)
    found = dealt.repartition(tasks, "parts").groupBy("parts").applyInPandas(counted, "n long")
    return found.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))
