"""From a configuration to a logical plan: one lookup join and one explode per loop, intersections as soon as they can be.

The loop plan is data (which arrays each loop needs, makes and drops); the emitter turns it into DataFrame calls. An
``explode_outer`` whose nulls the next predicate drops is used instead of ``explode``: for the latter the optimiser infers a
filter on the array's size and evaluates the intersection again.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import Graph, column_of, may_replicate
from .patterns import Pattern
from .planner import Configuration
from .symmetry import closure

#: An operand is a bound vertex and which of its lists: ("n" | "o" | "i", edge label).
Operand = tuple[int, str, str | None]


@dataclass(frozen=True)
class Loop:
    vertex: int
    candidates: tuple[Operand, ...]
    above: tuple[int, ...]  # bound vertices whose id must be larger
    below: tuple[int, ...]  # bound vertices whose id must be smaller
    apart: tuple[int, ...]  # bound vertices it could coincide with
    barred: tuple[int, ...]  # bound vertices it must not be adjacent to (induced matching)
    lists: tuple[Operand, ...]  # lists to look up once bound
    temps: tuple[tuple[Operand, ...], ...]  # intersections to take once bound
    live: frozenset[tuple[Operand, ...]]  # arrays needed by later loops
    sizes: tuple[Operand, ...] = ()  # lists of which the length alone is looked up
    least: tuple[int, ...] = ()  # members that each of the temps must have for any match


def lists_with(p: Pattern, u: int, v: int) -> list[Operand]:
    """Lists of u that hold v, if v is adjacent to u."""
    marks = dict(zip(p.edges, p.elabels or [None] * len(p.edges), strict=True))
    if not p.directed:
        e = tuple(sorted((u, v)))
        return [(u, "n", marks[e])] if e in marks else []
    return [(u, way, marks[e]) for way, e in (("o", (u, v)), ("i", (v, u))) if e in marks]


def members(p: Pattern, operands: tuple[Operand, ...]) -> int:
    """How many vertices of the pattern are in all these lists; they bind different ids, so an intersection with fewer leads to none."""
    return sum(all(x in lists_with(p, x[0], v) for x in operands) for v in range(p.n) if all(x[0] != v for x in operands))


def loop_plan(c: Configuration, loops: int | None = None, restrictions=None, induced: bool = False, arrays: tuple[tuple[Operand, ...], ...] | None = None, sizes: tuple[Operand, ...] = ()) -> list[Loop]:
    """Plan of the first ``loops`` loops; arrays the remaining ones range over are kept live.

    arrays: keep these instead, for what takes the place of the remaining loops; sizes: and the lengths of these lists.
    """
    p, order = c.pattern, c.order
    loops = p.n if loops is None else loops
    rules = closure(c.restrictions if restrictions is None else restrictions)
    at = {v: i for i, v in enumerate(order)}
    candidates = [tuple(x for u in order[:i] for x in lists_with(p, u, v)) for i, v in enumerate(order)]
    barred = [tuple(u for u in order[:i] if induced and not p.adjacent(u, v)) for i, v in enumerate(order)]
    if arrays is not None:
        candidates[loops:] = arrays
    made: dict[tuple[Operand, ...], int] = {}
    for s in candidates:
        for q in range(2, len(s) + 1):
            made.setdefault(s[:q], at[s[q - 1][0]])
    out = []
    for i in range(loops):
        v = order[i]
        needed: set[tuple[Operand, ...]] = set(candidates[i + 1 :])
        needed |= {t[:-1] for t, where in made.items() if where > i} | {(t[-1],) for t, where in made.items() if where > i and at[t[-1][0]] <= i}
        needed |= {((u, "n", None),) for b in barred[i + 1 :] for u in b}
        here = {x for t, where in made.items() if where == i for x in (t[-1],)} | {x for s in needed for x in s if len(s) == 1}
        temps = tuple(t for t, where in made.items() if where == i)
        out.append(
            Loop(
                v, candidates[i],
                tuple(a for a, b in sorted(rules) if b == v and at[a] < i), tuple(b for a, b in sorted(rules) if a == v and at[b] < i),
                tuple(u for u in order[:i] if not p.adjacent(u, v) and not {(u, v), (v, u)} & rules), barred[i],
                tuple(sorted((x for x in here if x[0] == v), key=str)),
                temps,
                frozenset(s for s in needed if s and all(at[x[0]] <= i for x in s)),
                tuple(x for x in sizes if x[0] == v),
                tuple(members(p, t) for t in temps),
            )
        )
    return out


def array_name(c: Configuration, operands: tuple[Operand, ...]) -> str:
    return "_".join(("l" if len(operands) == 1 else "t", *(f"{c.pattern.names[u]}{way}{mark or ''}" for u, way, mark in operands)))


def size_name(c: Configuration, x: Operand) -> str:
    return "d" + array_name(c, (x,))


def lookup(graph: Graph, plan: list[Loop], c: Configuration) -> DataFrame:
    """The neighbour table with the lists this plan uses."""
    kinds = tuple(sorted({(way, mark) for loop in plan for _, way, mark in (*loop.lists, *(x for x in loop.sizes if x[1:] != ("n", None)))} or {("n", None)}, key=str))
    return graph.adjacency(kinds)


def in_flight(graph: Graph, plan: list[Loop]) -> float:
    """Bytes that the plan's lookups would send, as estimated: rows by the mean list of an edge's end and the share of closed wedges."""
    ends, squares = graph.moments()
    if not ends:
        return 0.0
    mean, closed = squares / ends, min(1.0, 6 * graph.stats().n_triangles / max(1, squares - ends))
    rows, total = float(graph.stats().n_vertices), 0.0
    for i, loop in enumerate(plan[1:], 1):
        rows *= mean * closed ** (len(loop.candidates) - 1) * (0.5 if loop.above or loop.below else 1.0)
        if loop.lists or loop.sizes:
            total += rows * 8 * (i + 1 + sum(mean * closed ** (len(s) - 1) for s in plan[i - 1].live))
    return total


def replicable(graph: Graph, plan: list[Loop]) -> bool:
    """Whether the lists that the plan looks up are few enough to go to every task whole, so that no row is shuffled to them."""
    kinds = {(way, mark) for loop in plan for _, way, mark in (*loop.lists, *loop.sizes)}
    return may_replicate(8 * graph.moments()[0] * max(1, len(kinds)) + 64 * graph.stats().n_vertices)


def emit(graph: Graph, c: Configuration, plan: list[Loop], hint: str | None = None, seeds: Column | None = None, prune: bool = False, deal: int = 0) -> DataFrame:
    """A row per binding of the plan's vertices: their columns, and the arrays live after the last loop.

    hint: join hint of the lookups ("broadcast", "merge", "shuffle_hash"); without one Spark goes by size.
    seeds: condition on ``id``, the first vertex. prune: a row whose intersections have too few members for any match ends at the next
    loop's explode, where it costs no second evaluation as a filter would. deal: the first vertex's rows go to that many partitions.
    """
    p = c.pattern
    table = lookup(graph, plan, c)
    label = p.vlabels or [None] * p.n
    col = lambda v: F.col(p.names[v])
    df = None
    bound: list[str] = []
    arrays: set[str] = set()
    enough: list[Column] = []
    for loop in plan:
        v, name = loop.vertex, p.names[loop.vertex]
        got = [F.col(column_of(way, mark)).alias(array_name(c, ((v, way, mark),))) for _, way, mark in loop.lists]
        got += [(F.col("deg") if x[1:] == ("n", None) else F.size(column_of(*x[1:]))).alias(size_name(c, x)) for x in loop.sizes]
        rows = table.where(F.col("deg") >= len(p.around[v]))
        if label[v] is not None:
            rows = rows.where(F.col("label") == label[v])
        rows = rows.select(F.col("id").alias(name), *got)
        if df is None:
            df = rows.where(seeds) if seeds is not None and not got else (table.where(seeds).where(F.col("deg") >= len(p.around[v])).where(F.col("label") == label[v] if label[v] is not None else F.lit(True)).select(F.col("id").alias(name), *got) if seeds is not None else rows)
            if deal:
                df = df.repartition(deal, name)
        else:
            source = F.col(array_name(c, loop.candidates))
            df = df.select(*bound, *sorted(arrays), F.explode_outer(F.when(reduce(and_, enough), source) if enough else source).alias(name))
            ok = F.col(name).isNotNull()
            for u in loop.above:
                ok &= col(v) < col(u)
            for u in loop.below:
                ok &= col(v) > col(u)
            for u in loop.apart:
                ok &= col(v) != col(u)
            for u in loop.barred:
                ok &= ~F.array_contains(array_name(c, ((u, "n", None),)), col(v))
            df = df.where(ok)
            if got or label[v] is not None:
                df = df.join(rows.hint(hint) if hint else rows, name)
        bound += [name, *(size_name(c, x) for x in loop.sizes)]
        arrays |= {array_name(c, (x,)) for x in loop.lists}
        made = {array_name(c, t): F.array_intersect(array_name(c, t[:-1]), array_name(c, t[-1:])) for t in loop.temps}
        step: dict[str, Column] = {}
        for t in sorted(loop.temps, key=len):  # a temporary may start from one made in this same loop
            key = array_name(c, t)
            if len(t) > 2 and array_name(c, t[:-1]) in step:
                df = df.select(*bound, *sorted(arrays), *(x.alias(k) for k, x in step.items()))
                arrays |= set(step)
                step = {}
            step[key] = made[key]
        arrays |= set(step)
        keep = sorted(a for a in arrays if a in {array_name(c, s) for s in loop.live})
        df = df.select(*bound, *(step[a].alias(a) if a in step else F.col(a) for a in keep))
        arrays = set(keep)
        enough = [F.size(array_name(c, t)) >= n for t, n in zip(loop.temps, loop.least, strict=True) if prune and array_name(c, t) in arrays]
    return df
