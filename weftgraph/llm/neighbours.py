"""Approximate nearest neighbours by inner product, with multiprobe p-stable hashing.

Vectors get one more coordinate that makes all norms equal, and queries a zero there, so that the largest inner product is the
smallest Euclidean distance, for which the hashes are made. A table's bucket is ``functions`` projections on Gaussian directions, each cut into
cells ``width`` wide. A query visits its own bucket and then perturbed ones, in order of estimated success: a step
over a cell wall costs its squared distance to the wall, and a heap yields sets of steps by summed cost. All
visited buckets of all tables give candidates, which are scored exactly in double precision.

Tables, functions, cell width and probes are chosen by what they do to a bounded sample (``choose``): the exact neighbours of PILOT
queries among all vectors give the recall of each choice, and BACKGROUND vectors the share that it would score; the cheapest
choice whose mean recall is two standard errors above ``recall`` is taken, or the one with the best recall if none is. Every
vector is indexed.

Vectors travel to their buckets once per table and queries to the buckets they visit; a bucket scores its queries
by one matrix product and keeps each one's best ``k``, so what is merged per query is tables x probes x k rows at
most. Buckets of more than ``block`` vectors or queries are split into a grid of blocks. Queries that found fewer
than ``k`` are compared with all vectors, in blocks. ``scored`` tells how many products a query took, a vector counted
each time it was met.

Vectors null, zero, of another length than most, or with null or non-finite components take no part. Rows that
share an id are one neighbour, with the best of their scores. No vectors give no rows.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, cut, read


#: Sample queries, and vectors taken to stand for all, when the index is fitted; both by smallest hash of the id.
PILOT, BACKGROUND = 64, 4096
#: What is tried: functions a table, cell width in radii, tables, probes a table.
FUNCTIONS, WIDTHS, TABLES, PROBES = (4, 6, 8, 12, 16), (1.0, 2.0), (1, 2, 4), (4, 12, 24, 48, 96)
#: A visited bucket costs about as much as so many products.
BUCKET_COST = 32


def perturbations(inside: np.ndarray, probes: int) -> list[list[tuple[int, int]]]:
    """The likeliest ``probes`` - 1 sets of (function, step) for fractions ``inside`` their cells, after the empty set."""
    walls = sorted([(x * x, m, -1) for m, x in enumerate(inside.tolist())] + [((1 - x) ** 2, m, 1) for m, x in enumerate(inside.tolist())])
    out, heap = [[]], [(walls[0][0], (0,))]
    while heap and len(out) < probes:
        cost, chosen = heapq.heappop(heap)
        if len({walls[i][1] for i in chosen}) == len(chosen):
            out.append([walls[i][1:] for i in chosen])
        last = chosen[-1]
        if last + 1 < len(walls):
            heapq.heappush(heap, (cost - walls[last][0] + walls[last + 1][0], (*chosen[:-1], last + 1)))
            heapq.heappush(heap, (cost + walls[last + 1][0], (*chosen, last + 1)))
    return out


class Tables:
    """The random directions and offsets; everything follows from the seed."""

    def __init__(self, dim: int, radius: float, tables: int, functions: int, width: float, seed: int):
        rng = np.random.default_rng(seed)
        self.radius, self.functions = radius, functions
        self.directions = rng.normal(size=(tables, dim + 1, functions)) / (width * radius)
        self.offsets = rng.uniform(size=(tables, functions))
        self.mixers = rng.integers(1, 1 << 62, functions, dtype=np.int64) | 1

    def cells(self, table: int, x: np.ndarray, query: bool) -> np.ndarray:
        extra = np.zeros(len(x)) if query else np.sqrt(np.maximum(0, self.radius**2 - (x * x).sum(1)))
        return np.column_stack((x, extra)) @ self.directions[table] + self.offsets[table]

    def bucket(self, cells: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return (cells.astype(np.int64) * self.mixers).sum(-1)


def _stack(batch: pa.RecordBatch) -> np.ndarray:
    return np.frombuffer(b"".join(batch.column("v").to_pylist()), np.float64).reshape(len(batch), -1)


def _rows(table, bucket, ids, vectors) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(table, pa.int32()), pa.array(bucket, pa.int64()), pa.array(ids, pa.int64()), pa.array(vectors, pa.binary())], ["t", "bucket", "id", "v"])


def best(ids: np.ndarray, x: np.ndarray, query_ids: np.ndarray, q: np.ndarray, k: int, products_at_once: int = 1 << 21) -> tuple[list, list, list]:
    """Each query's k best of x, by (score, smaller id); near ties of the matrix product are scored row by row."""
    out: tuple[list, list, list] = ([], [], [])
    step = max(1, products_at_once // max(1, len(x)))
    for begin in range(0, len(q), step):
        part = q[begin : begin + step]
        for qid, v, s in zip(query_ids[begin : begin + step].tolist(), part, part @ x.T, strict=True):
            ok = ids != qid
            if k < len(s):
                floor = np.partition(np.where(ok, s, -np.inf), len(s) - k)[len(s) - k]
                ok &= s >= floor - 1e-9 * (1 + abs(floor)) if np.isfinite(floor) else True
            at = np.flatnonzero(ok)
            exact = (x[at] * v).sum(axis=1)
            order = np.lexsort((ids[at], -exact))[:k]
            out[0].extend([qid] * len(order))
            out[1].extend(ids[at[order]].tolist())
            out[2].extend(exact[order].tolist())
    return out


def visits(shape: Tables, table: int, q: np.ndarray, probes: int) -> list[np.ndarray]:
    """The buckets that each query visits, likeliest first."""
    cells = shape.cells(table, q, True)
    floors = np.floor(cells)
    out = []
    for low, inside in zip(floors, cells - floors, strict=True):
        sets = perturbations(inside, probes)
        goals = np.repeat(low[None], len(sets), axis=0)
        for goal, steps in zip(goals, sets, strict=True):
            for m, step in steps:
                goal[m] += step
        out.append(shape.bucket(goals))
    return out


def choose(near: list[np.ndarray], queries: np.ndarray, background: np.ndarray, n: int, radius: float, seed: int, recall: float) -> dict:
    """tables, functions, width and probes, with the recall and the scored share they have on the sample.

    near: the true neighbours of each sample query. n: vectors in all.
    """
    found = []
    sizes_near = np.array([len(x) for x in near])
    some, owner = sizes_near > 0, np.repeat(np.arange(len(near)), sizes_near)
    for functions in FUNCTIONS:
        for width in WIDTHS:
            shape = Tables(queries.shape[1], radius, max(TABLES), functions, width, seed)
            first, share = [], []  # at which probe a table finds each neighbour; how many background vectors it has met by then
            for t in range(max(TABLES)):
                own = visits(shape, t, queries, max(PROBES))
                place = [dict(zip(reversed(v.tolist()), range(len(v) - 1, -1, -1), strict=True)) for v in own]
                hit = [[p.get(b, 1 << 30) for b in shape.bucket(np.floor(shape.cells(t, x, False))).tolist()] for p, x in zip(place, near, strict=True)]
                first.append(np.concatenate([np.array(h, np.int64) for h in hit]))
                buckets, counts = np.unique(shape.bucket(np.floor(shape.cells(t, background, False))), return_counts=True)
                sizes = dict(zip(buckets.tolist(), counts.tolist(), strict=True))
                share.append(np.mean([np.cumsum([sizes.get(b, 0) for b in np.pad(v, (0, max(PROBES) - len(v)), constant_values=0).tolist()]) for v in own], axis=0) / len(background))
            for tables in TABLES:
                for probes in PROBES:
                    hits = np.bincount(owner, np.min(first[:tables], axis=0) < probes, len(near))[some] / sizes_near[some]
                    got = float(hits.mean()) if len(hits) else 0.0
                    sure = got - 2 * float(hits.std()) / max(1, len(hits)) ** 0.5
                    scored = float(sum(s[probes - 1] for s in share[:tables]))
                    found.append({"tables": tables, "functions": functions, "width": width, "probes": probes, "recall": got, "sure": sure, "scored": scored, "cost": scored * n + BUCKET_COST * tables * probes})
    good = [c for c in found if c["sure"] >= recall]
    return min(good, key=lambda c: c["cost"]) if good else max(found, key=lambda c: (c["recall"], -c["cost"]))


def _score_blocks(index: DataFrame, probes: DataFrame, k: int, block: int) -> DataFrame:
    """index and probes: t, bucket, id, v. Each bucket's best k of each query."""
    key = ["t", "bucket"]
    n = index.groupBy(*key).agg(F.count(F.lit(1)).alias("n")).join(probes.groupBy(*key).agg(F.count(F.lit(1)).alias("m")), key)
    grid = cut(n.select(*key, F.ceil(F.col("n") / block).cast("int").alias("rows"), F.ceil(F.col("m") / block).cast("int").alias("cols")))

    def dealt(df: DataFrame, own: str, other: str, query: bool) -> DataFrame:
        split = df.join(grid, key)
        return split.select(
            *key, F.pmod(F.xxhash64("id"), F.col(own)).cast("int").alias(own), F.explode(F.sequence(F.lit(0), F.col(other) - 1)).alias(other), "id", "v", F.lit(query).alias("query")
        ).select(*key, "rows", "cols", "id", "v", "query")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        asks = pdf["query"].to_numpy(bool)
        mat = np.frombuffer(b"".join(pdf["v"]), np.float64).reshape(len(pdf), -1)
        ids = pdf["id"].to_numpy(np.int64)
        if asks.all() or not asks.any():
            return pd.DataFrame({"query_id": np.zeros(0, np.int64), "vec_id": np.zeros(0, np.int64), "score": np.zeros(0), "scored": np.zeros(0, np.int64)})
        qs, vs, ss = best(ids[~asks], mat[~asks], ids[asks], mat[asks], k)
        rows = pd.DataFrame({"query_id": qs, "vec_id": vs, "score": ss})
        rows["scored"] = 0
        rows.loc[~rows["query_id"].duplicated(), "scored"] = int((~asks).sum())  # once a query
        return rows

    both = dealt(index, "rows", "cols", False).unionByName(dealt(probes, "cols", "rows", True))
    return both.groupBy(*key, "rows", "cols").applyInPandas(run, "query_id long, vec_id long, score double, scored long")


def _merge(found: DataFrame, k: int) -> DataFrame:
    """Each query's best k distinct neighbours, as an array of (negative score, id), and its products."""
    single = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"), F.sum("scored").alias("scored"))
    return single.groupBy("query_id").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("s"), "vec_id"))), 1, k).alias("best"), F.sum("scored").alias("scored"))


def _fit(vectors: DataFrame, k: int, n: int, radius: float, seed: int, recall: float) -> dict:
    """choose() on a bounded sample: PILOT queries with their exact neighbours among all vectors, and BACKGROUND vectors."""
    by_hash = lambda df, rows: df.select("id", "v").orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(rows).toPandas()
    pilot, back = by_hash(vectors.where("ask"), PILOT), by_hash(vectors, BACKGROUND)
    unpack = lambda col: np.frombuffer(b"".join(col), np.float64).reshape(len(col), -1)
    q_ids, q = pilot["id"].to_numpy(np.int64), unpack(pilot["v"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if len(b):
                ids, x = b.column("id").to_numpy(), _stack(b)
                qs, vs, ss = best(ids, x, q_ids, q, k)
                at = dict(zip(ids.tolist(), x, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(qs, pa.int64()), pa.array(vs, pa.int64()), pa.array(ss, pa.float64()), pa.array([at[v].tobytes() for v in vs], pa.binary())], ["query_id", "vec_id", "score", "v"])

    found = arrow_map(vectors.select("id", "v"), run, "query_id long, vec_id long, score double, v binary")
    top = found.groupBy("query_id").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("s"), "vec_id", "v"))), 1, k).alias("best"))
    near = {r["query_id"]: unpack([x["v"] for x in r["best"]]) for r in top.collect()}
    return choose([near.get(i, np.zeros((0, q.shape[1]))) for i in q_ids.tolist()], q, unpack(back["v"]), n, radius, seed, recall)


def nearest(
    df: DataFrame, is_query: Column, k: int = 20, id_column: str = "vec_id", vector: str = "embedding",
    index: dict | None = None, recall: float = 0.9, block: int = 4096, seed: int = 11,
) -> DataFrame:
    """query_id, rank (from 1), vec_id, score, scored: neighbours of the rows for which ``is_query`` holds, among all others.

    index: tables, functions, width and probes; fitted for ``recall`` on a sample if not given.
    """
    rows = df.select(F.col(id_column).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("x"), F.coalesce(is_query, F.lit(False)).alias("ask")).where("id is not null and x is not null")
    common = rows.groupBy(F.size("x").alias("d")).count().where("d > 0").orderBy(F.desc("count"), "d").first()
    spark = df.sparkSession
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double, scored long")
    if common is None:
        return empty
    dim = common["d"]

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = b.column("x").flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(b), dim)
            ok = np.isfinite(x).all(axis=1) & (x != 0).any(axis=1)
            at = pa.array(np.flatnonzero(ok))
            norms = np.sqrt((x[ok] ** 2).sum(axis=1))
            yield pa.RecordBatch.from_arrays([b.column("id").take(at), b.column("ask").take(at), pa.array([v.tobytes() for v in x[ok]], pa.binary()), pa.array(norms)], ["id", "ask", "v", "norm"])

    vectors = cut(arrow_map(rows.where(F.size("x") == dim), clean, "id long, ask boolean, v binary, norm double"))
    radius, n, asked = vectors.agg(F.max("norm"), F.count(F.lit(1)), F.count_if("ask")).first()
    if not asked:
        return empty
    index = index or _fit(vectors, k, n, radius, seed, recall)
    tables, probes = index["tables"], index["probes"]
    shape = Tables(dim, radius, tables, index["functions"], index["width"], seed)

    def post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if len(b):
                x = _stack(b)
                for t in range(tables):
                    yield _rows(np.full(len(b), t), shape.bucket(np.floor(shape.cells(t, x, False))), b.column("id"), b.column("v"))

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not len(b):
                continue
            x = _stack(b)
            for t in range(tables):
                own = visits(shape, t, x, probes)
                at = pa.array(np.repeat(np.arange(len(own)), [len(v) for v in own]))
                yield _rows(np.full(len(at), t), np.concatenate(own), b.column("id").take(at), b.column("v").take(at))

    schema = "t int, bucket long, id long, v binary"
    queries = vectors.where("ask")
    found = _score_blocks(arrow_map(vectors.select("id", "v"), post, schema), arrow_map(queries.select("id", "v"), visit, schema), k, block)
    merged = cut(_merge(found, k))
    short = queries.join(merged.where(F.size("best") >= k).select(F.col("query_id").alias("id")), "id", "left_anti").select(F.lit(-1).alias("t"), F.lit(0).cast("long").alias("bucket"), "id", "v")
    if not short.isEmpty():
        every = vectors.select(F.lit(-1).alias("t"), F.lit(0).cast("long").alias("bucket"), "id", "v")
        rest = cut(_merge(_score_blocks(every, short, k, block), k))
        merged = merged.join(rest.select("query_id"), "query_id", "left_anti").unionByName(rest)
    return merged.select("query_id", "scored", F.posexplode("best").alias("p", "b")).select("query_id", (F.col("p") + 1).cast("int").alias("rank"), F.col("b.vec_id").alias("vec_id"), (-F.col("b.s")).alias("score"), "scored")


def op3_multiprobe_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(read(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)
