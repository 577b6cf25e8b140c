"""Other ways to run a plan: a replicated graph with prefix tasks, and neighbour lists too long for one row.

``spread`` is for graphs with hubs. The list plans hold a vertex's neighbours in one row and look it up under its id, so a hub is
one long row, met in one task by all prefixes that end in it. Here lists are cut into chunks, a prefix meets each
chunk of its shortest list under (id, chunk, salt), and what it finds is checked against the edges by joins on pairs of ids,
which no hub makes hot. No array is longer than a chunk, and none is carried.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import compiler, planner
from ..plans.patterns import Pattern
from ..shipping import ship
from ..sources.graphs import Graph, chunk_count, in_classes, oriented, salt_count

#: The replicated graph may take this many bytes on the driver and on each executor.
MAX_BROADCAST_BYTES = 256 << 20
#: Neighbours in a row of the chunk table, and the degree from which on lists are not carried.
CHUNK, HUB_DEGREE = 1024, 100_000
#: List members that the replicated executor holds for its prefixes at once.
PAIRS_AT_ONCE = 1 << 21


class Csr:
    """Sorted neighbour lists in two arrays, over ids compacted to 0.. in id order."""

    def __init__(self, ids: np.ndarray, offsets: np.ndarray, targets: np.ndarray):
        self.ids, self.offsets, self.targets = ids, offsets, targets

    @cached_property
    def keys(self) -> np.ndarray:
        """One sorted number a directed edge, to look pairs up."""
        return np.repeat(np.arange(len(self.ids)), np.diff(self.offsets)) * len(self.ids) + self.targets

    def adjacent(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        want = a * len(self.ids) + b
        at = np.minimum(np.searchsorted(self.keys, want), max(0, len(self.keys) - 1))
        return self.keys[at] == want if len(self.keys) else np.zeros(len(want), bool)


def csr_bytes(g: Graph) -> int:
    """Of the two arrays and the pair numbers; the driver takes some four times that while it sorts."""
    s = g.stats()
    return 16 * s.n_vertices + 32 * s.n_edges


def to_csr(g: Graph, limit: int = MAX_BROADCAST_BYTES) -> Csr:
    """The whole graph on the driver; refused beyond ``limit`` bytes, for which there are the join plans."""
    if (size := csr_bytes(g)) > limit:
        raise ValueError(f"the graph takes {size} bytes replicated; the limit is {limit}: use the join plans")
    e = g.edges.select("src", "dst").toPandas().to_numpy(np.int64).reshape(-1, 2)
    both = np.concatenate((e, e[:, ::-1]))
    ids = np.unique(both)
    both = np.searchsorted(ids, both)
    both = both[np.lexsort((both[:, 1], both[:, 0]))]
    return Csr(ids, np.searchsorted(both[:, 0], np.arange(len(ids) + 1)), both[:, 1].copy())


class Prefixes:
    """Many bindings side by side: a column of vertex numbers per bound vertex, and per kept intersection its members
    in one array with a row number for each."""

    def __init__(self, csr: Csr, rows: dict[int, np.ndarray]):
        self.csr, self.rows, self.sets = csr, rows, {}

    def __len__(self) -> int:
        return len(next(iter(self.rows.values())))

    def neighbours(self, v: int) -> tuple[np.ndarray, np.ndarray]:
        """(row, member) of the lists of the vertex bound to v, row by row and sorted."""
        at = self.rows[v]
        begins, sizes = self.csr.offsets[at], self.csr.offsets[at + 1] - self.csr.offsets[at]
        row = np.repeat(np.arange(len(at)), sizes)
        return row, self.csr.targets[np.arange(len(row)) - np.repeat(np.cumsum(sizes) - sizes, sizes) + np.repeat(begins, sizes)]

    def members(self, operands) -> tuple[np.ndarray, np.ndarray]:
        """(row, member) of an intersection of lists: those of the first that the others hold."""
        if operands not in self.sets:
            if len(operands) == 1:
                self.sets[operands] = self.neighbours(operands[0][0])
            else:
                row, member = self.members(operands[:-1])
                ok = self.csr.adjacent(self.rows[operands[-1][0]][row], member)
                self.sets[operands] = row[ok], member[ok]
        return self.sets[operands]

    def candidates(self, loop: compiler.Loop) -> tuple[np.ndarray, np.ndarray]:
        """(row, vertex) that the loop binds."""
        row, found = self.members(loop.candidates)
        ok = np.ones(len(row), bool)
        for u in loop.above:
            ok &= found < self.rows[u][row]
        for u in loop.below:
            ok &= found > self.rows[u][row]
        for u in loop.apart:
            ok &= found != self.rows[u][row]
        return row[ok], found[ok]

    def part(self, begin: int, end: int) -> Prefixes:
        return Prefixes(self.csr, {v: x[begin:end] for v, x in self.rows.items()})


def count_prefixes(csr: Csr, plan: list[compiler.Loop], rows: dict[int, np.ndarray], i: int) -> int:
    """Run the loops from ``i`` on for all prefixes at once; the last is counted, not run.

    Prefixes that would find more than PAIRS_AT_ONCE members are halved first, and what a loop binds goes on in parts.
    """
    here = Prefixes(csr, rows)
    loop = plan[i]
    first = rows[loop.candidates[0][0]]
    work = np.cumsum(csr.offsets[first + 1] - csr.offsets[first])
    if len(here) > 1 and work[-1] > PAIRS_AT_ONCE:
        cut = int(np.clip(np.searchsorted(work, work[-1] // 2), 1, len(here) - 1))
        return sum(count_prefixes(csr, plan, part.rows, i) for part in (here.part(0, cut), here.part(cut, len(here))))
    row, found = here.candidates(loop)
    if i == len(plan) - 1:
        return len(found)
    return count_prefixes(csr, plan, {v: x[row] for v, x in rows.items()} | {loop.vertex: found}, i + 1) if len(found) else 0


def default_depth(p: Pattern) -> int:
    """Outer loops run as tasks: one for patterns of up to three vertices, two for larger ones."""
    return 1 if p.n <= 3 else 2


def prefix_tasks(g: Graph, c: planner.Configuration, depth: int | None = None, partitions: int | None = None) -> DataFrame:
    """Bindings of the first loops, dealt by hash over many more partitions than cores, so that none waits long."""
    depth = default_depth(c.pattern) if depth is None else depth
    names = [c.pattern.names[v] for v in c.order[:depth]]
    rows = compiler.emit(g, c, compiler.loop_plan(c)[:depth]).select(*names)
    return rows.repartition(partitions or 16 * g.spark.sparkContext.defaultParallelism, *names)


def replicated_count(g: Graph, p: Pattern, config: planner.Configuration | None = None, depth: int | None = None, partitions: int | None = None, name: str | None = None) -> DataFrame:
    """Count with the graph replicated to every executor and one task per group of prefixes, which run side by side in numpy."""
    if p.directed or p.vlabels:
        raise ValueError("the replicated executor runs undirected, unlabelled patterns")
    c = config or planner.choose(p, g.stats())
    ship(g.spark)
    shared = g.spark.sparkContext.broadcast(to_csr(g))  # size checked
    depth = default_depth(p) if depth is None else depth
    plan = compiler.loop_plan(c)
    names = [p.names[v] for v in c.order[:depth]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        csr = shared.value
        for b in batches:
            cols = [np.searchsorted(csr.ids, b.column(x).to_numpy()) for x in names]
            rows = {loop.vertex: x for loop, x in zip(plan, cols, strict=False)}
            total = count_prefixes(csr, plan, rows, depth) if len(b) else 0
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], ["n"])

    counted = prefix_tasks(g, c, depth, partitions).mapInArrow(run, "n long")
    return counted.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).select(F.lit(name or p.text()).alias("pattern"), "n")


def spread(g: Graph, c: planner.Configuration, size: int = CHUNK, loops: int | None = None, seeds=None) -> DataFrame:
    """A row per binding of the first ``loops`` vertices (all by default) of an undirected, unlabelled pattern; seeds: condition on
    ``id``, the first vertex."""
    p = c.pattern
    if p.directed or p.vlabels or p.elabels:
        raise ValueError("the spread executor runs undirected, unlabelled patterns")
    chunks, names = g.chunks(size), p.names
    plan = compiler.loop_plan(c)[:loops]
    first = names[plan[0].vertex]
    df = g.degrees().where(seeds if seeds is not None else F.lit(True)).where(F.col("deg") >= len(p.around[plan[0].vertex])).select(F.col("id").alias(first), F.col("deg").alias(f"d_{first}"))
    for loop in plan[1:]:
        name, near = names[loop.vertex], [names[x[0]] for x in loop.candidates]
        bound = df.columns
        shortest = F.least(*(F.struct(F.col(f"d_{u}").alias("deg"), F.col(u).alias("id")) for u in near)) if len(near) > 1 else F.struct(F.col(f"d_{near[0]}").alias("deg"), F.col(near[0]).alias("id"))
        asks = df.select(*bound, shortest.alias("of")).select(*bound, F.col("of.id").alias("id"), F.col("of.deg").alias("deg"))
        salt = F.pmod(F.xxhash64(*(names[x.vertex] for x in plan[: plan.index(loop)])), salt_count(F.col("deg"), size)).cast("int")
        asks = asks.select(*bound, "id", salt.alias("salt"), F.explode(F.sequence(F.lit(0), chunk_count(F.col("deg"), size) - 1)).alias("chunk"))
        found = asks.join(chunks.select("id", "chunk", "salt", "nbrs"), ["id", "chunk", "salt"]).select(*bound, "id", F.explode("nbrs").alias("x"))
        df = found.select(*bound, "id", F.col("x.nbr").alias(name), F.col("x.nd").alias(f"d_{name}"))
        ok = F.col(f"d_{name}") >= len(p.around[loop.vertex])
        for u in loop.above:
            ok &= F.col(name) < F.col(names[u])
        for u in loop.below:
            ok &= F.col(name) > F.col(names[u])
        for u in loop.apart:
            ok &= F.col(name) != F.col(names[u])
        df = df.where(ok)
        for u in near if len(near) > 1 else []:  # the list it came from holds it; the others are asked
            pair = df.withColumns({"src": F.least(u, name), "dst": F.greatest(u, name)})
            df = pair.join(g.edges.select("src", "dst"), ["src", "dst"], "left_semi").drop("src", "dst")
        df = df.drop("id")
    return df.select(*(names[x.vertex] for x in plan))


def spread_count(g: Graph, p: Pattern, config: planner.Configuration | None = None, size: int = CHUNK, name: str | None = None) -> DataFrame:
    c = config or planner.choose(p, g.stats())
    ends, squares = g.moments()
    rows, sent = float(g.stats().n_vertices), 0.0
    for i in range(1, p.n):  # what a loop binds goes to the next one's chunks, with the degrees
        sent += rows * 8 * (2 * i + 3)
        rows *= squares / max(1, ends)
    return in_classes(g, sent, lambda own: spread(g, c, size, seeds=own).agg(F.count(F.lit(1)).alias("n")), "n long").select(F.lit(name or p.text()).alias("pattern"), "n")


def has_hubs(g: Graph) -> bool:
    """Whether some list is too long to travel in rows."""
    return g.max_degree() > HUB_DEGREE


def chunked(g: Graph, size: int) -> DataFrame:
    """id, chunk, nbrs: neighbour lists cut into rows of at most ``size``, so that no hub is one huge row.

    A list is dealt over its chunks by hash before it is gathered; no task sees a whole hub.
    """
    both = g.edges.select(F.col("src").alias("id"), F.col("dst").alias("nbr")).unionByName(g.edges.select(F.col("dst").alias("id"), F.col("src").alias("nbr")))
    deg = both.groupBy("id").agg(F.count(F.lit(1)).alias("deg"))
    parts = both.join(deg, "id").withColumn("chunk", F.pmod(F.xxhash64("nbr"), F.ceil(F.col("deg") / size)).cast("int"))
    return parts.groupBy("id", "chunk").agg(F.sort_array(F.collect_list("nbr")).alias("nbrs"))


def chunked_triangles(g: Graph, size: int) -> DataFrame:
    """Triangles with chunked lists: an edge's ends meet chunk by chunk, and the shared neighbours add up."""
    up = oriented(g)
    deg = up.groupBy("a").agg(F.count(F.lit(1)).alias("n"))
    dealt = up.join(deg, "a").withColumn("chunk", F.pmod(F.xxhash64("b"), F.ceil(F.col("n") / size)).cast("int"))
    lists = dealt.groupBy("a", "chunk").agg(F.collect_list("b").alias("s"))
    pairs = up.join(lists, "a").select("b", "s").join(lists.select(F.col("a").alias("b"), F.col("s").alias("t")), "b")
    return pairs.agg(F.coalesce(F.sum(F.size(F.array_intersect("s", "t"))), F.lit(0)).cast("long").alias("n_triangles"))
