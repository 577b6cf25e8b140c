"""Measures of methods and plans: agreement, time, speed-up, regret, loop work, and how well costs predict them."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable
from dataclasses import dataclass
from functools import cache
from itertools import permutations, product
from math import prod
from statistics import mean

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import api
from .plans import compiler, cost_model, planner, schedules, symmetry
from .plans.patterns import Pattern
from .plans.planner import Configuration
from .sources.graphs import Graph

MEASUREMENTS = "pattern string, graph string, method string, n long, loop_work long, seconds double, status string"


@dataclass
class Timed:
    value: object
    seconds: float
    status: str  # ok, timeout, oom or error


def timed(g: Graph, run: Callable[[], DataFrame], timeout: float | None = None) -> Timed:
    """Run a one-row count; beyond ``timeout`` seconds its jobs are cancelled and the status says so."""
    sc = g.spark.sparkContext
    tag = f"timed-{time.monotonic_ns()}"
    g.spark.addTag(tag)
    ended, stopped = threading.Event(), threading.Event()

    def stop() -> None:
        if not ended.wait(timeout):
            stopped.set()
            while not ended.is_set():  # again and again: between two jobs of a query there is nothing to cancel
                sc.cancelJobsWithTag(tag)
                g.spark.interruptTag(tag)
                ended.wait(0.3)

    if timeout:
        threading.Thread(target=stop, daemon=True).start()
    began = time.perf_counter()
    try:
        value = run().first()["n"]
        return Timed(value, time.perf_counter() - began, "ok")
    except Exception as e:
        text = str(e)
        return Timed(None, time.perf_counter() - began, "timeout" if stopped.is_set() else "oom" if "OutOfMemory" in text else "error")
    finally:
        ended.set()
        g.spark.removeTag(tag)


def agree(g: Graph, p: Pattern, methods: dict[str, Callable[[], DataFrame]]) -> bool:
    """Whether all methods count the same."""
    return len({run().first()["n"] for run in methods.values()}) == 1


def speedup(base: list[float], ours: list[float]) -> tuple[float, float]:
    """Mean and maximum of the ratios, pair by pair."""
    ratios = [b / o for b, o in zip(base, ours, strict=True) if o]
    return (mean(ratios), max(ratios)) if ratios else (float("nan"), float("nan"))


@cache
def canonical(n: int, edges: tuple, rules: tuple) -> tuple[tuple, tuple[int, ...]]:
    """The least renumbering of a prefix, so that prefixes that look alike are counted once per graph, and the new number of each vertex."""
    degree = [(sum(v in e for e in edges), sum(a == v for a, _ in rules), sum(b == v for _, b in rules)) for v in range(n)]
    kinds = sorted(set(degree))
    slots = [[i for i, d in enumerate(sorted(degree)) if d == k] for k in kinds]
    owners = [[v for v in range(n) if degree[v] == k] for k in kinds]
    best = None
    for parts in product(*(permutations(s) for s in slots)):
        new = {v: i for vs, part in zip(owners, parts, strict=True) for v, i in zip(vs, part, strict=True)}
        made = (n, tuple(sorted(tuple(sorted((new[a], new[b]))) for a, b in edges)), tuple(sorted((new[a], new[b]) for a, b in rules)))
        if best is None or made < best[0]:
            best = made, tuple(new[v] for v in range(n))
    return best


class LoopWork:
    """Rows of each loop plus the lengths of both lists of every intersection taken there, measured on the graph.

    The rows of a loop are the bindings of its prefix, which is a smaller pattern with the prefix's inequalities, and an
    intersection is taken once for each of them. Prefixes that differ only in order are measured once.
    """

    def __init__(self, g: Graph):
        self.g, self.seen = g, g.__dict__.setdefault("_prefix_sums", {})

    @staticmethod
    def _key(p: Pattern, vertices, rules) -> tuple[tuple, dict[int, int]]:
        keep = sorted(vertices)
        at = {v: i for i, v in enumerate(keep)}
        edges = tuple(sorted(tuple(sorted((at[a], at[b]))) for a, b in p.edges if a in at and b in at))
        key, new = canonical(len(keep), edges, tuple(sorted((at[a], at[b]) for a, b in rules if a in at and b in at)))
        return key, {v: new[i] for v, i in at.items()}

    @staticmethod
    def _configuration(key: tuple) -> Configuration:
        n, edges, rules = key
        q = Pattern(tuple("ABCDEFGH"[:n]), edges)
        return Configuration(q, schedules.connected_prefix(schedules.all_orders(q), q)[0], frozenset(rules))

    def prefix_rows(self, p: Pattern, vertices: frozenset, rules) -> int:
        key, _ = self._key(p, vertices, rules)
        if key not in self.seen:
            if key[0] == 1:
                self.seen[key] = self.g.stats().n_vertices
            else:
                c = self._configuration(key)
                self.seen[key] = api.count(self.g, c.pattern, c, method="enumerate").first()["n"]
        return self.seen[key]

    def list_lengths(self, p: Pattern, vertices: frozenset, rules, of: tuple[int, ...]) -> int:
        """Summed over the prefix's bindings: how long the intersection of the neighbour lists of these vertices is."""
        key, new = self._key(p, vertices, rules)
        asked = tuple(sorted(new[v] for v in of))
        if (key, asked) not in self.seen:
            if key[0] == 1:
                self.seen[key, asked] = 2 * self.g.stats().n_edges
                return self.seen[key, asked]
            c = self._configuration(key)
            one = [(v, "n", None) for v in range(key[0])]  # all single lists in one run
            arrays = (tuple(one[v] for v in c.order if v in asked),) if len(asked) > 1 else ()
            plan = compiler.loop_plan(c, key[0], arrays=arrays, sizes=() if arrays else tuple(one))
            rows = compiler.emit(self.g, c, plan)
            total = lambda x: F.coalesce(F.sum(x.cast("long")), F.lit(0))
            if arrays:
                self.seen[key, asked] = rows.agg(total(F.size(compiler.array_name(c, arrays[0]))).alias("n")).first()["n"]
            else:
                sums = rows.agg(*(total(F.col(compiler.size_name(c, x))).alias(f"n{x[0]}") for x in one)).first()
                self.seen |= {(key, (v,)): sums[f"n{v}"] for v in range(key[0])}
        return self.seen[key, asked]

    def of(self, c: Configuration) -> int:
        rules, temps = symmetry.closure(c.restrictions), cost_model.temporaries(c.order, c.pattern)
        total = 0
        for i in range(c.pattern.n):
            prefix = frozenset(c.order[: i + 1])
            total += self.prefix_rows(c.pattern, prefix, rules)
            total += sum(self.list_lengths(c.pattern, prefix, rules, part) for t in temps[i] for part in (t[:-1], t[-1:]))
        return total


def rank_corr(xs: list[float], ys: list[float]) -> float:
    """Spearman's coefficient, ties averaged."""

    def ranks(v):
        order = sorted(range(len(v)), key=v.__getitem__)
        out = [0.0] * len(v)
        i = 0
        while i < len(v):
            j = i
            while j + 1 < len(v) and v[order[j + 1]] == v[order[i]]:
                j += 1
            for k in range(i, j + 1):
                out[order[k]] = (i + j) / 2
            i = j + 1
        return out

    a, b = ranks(xs), ranks(ys)
    ma, mb = mean(a), mean(b)
    top = sum((x - ma) * (y - mb) for x, y in zip(a, b, strict=True))
    low = prod(sum((x - m) ** 2 for x in v) ** 0.5 for v, m in ((a, ma), (b, mb)))
    return top / low if low else float("nan")


def qerror(predicted: float, actual: float) -> float:
    """The factor by which an estimate is off, either way."""
    a, b = max(predicted, 1e-9), max(actual, 1e-9)
    return max(a / b, b / a)


def rel_error(estimate: float, exact: float) -> float:
    return abs(estimate - exact) / exact if exact else float(estimate != 0)


def configurations(g: Graph, p: Pattern, phases: int = 2) -> list[Configuration]:
    return planner.rank(p, g.stats(), phases=phases)


def spread(g: Graph, p: Pattern, phases: int = 2) -> tuple[int, int, float]:
    """(least, most, most / least) loop work over all configurations."""
    meter = LoopWork(g)
    works = [meter.of(c) for c in configurations(g, p, phases)]
    return min(works), max(works), max(works) / max(1, min(works))


def regret(g: Graph, p: Pattern) -> float:
    """Loop work of the chosen configuration against the least of all, minus one."""
    meter = LoopWork(g)
    found = configurations(g, p)
    return meter.of(found[0]) / max(1, min(meter.of(c) for c in found)) - 1


def oracle(g: Graph, p: Pattern) -> Configuration:
    """The configuration with the least loop work, by measuring all."""
    meter = LoopWork(g)
    return min(configurations(g, p), key=lambda c: (meter.of(c), c.cost))


def enumerated(g: Graph, c: Configuration, timeout: float | None = None) -> Timed:
    return timed(g, lambda: api.count(g, c.pattern, c, method="enumerate"), timeout)


def set_pairs(g: Graph, p: Pattern) -> list[tuple[Configuration, Configuration]]:
    """Per order where they differ: (the single set, the set the model chooses)."""
    single = symmetry.closure(symmetry.orbit_restrictions(p))
    best = [planner.choose(p, g.stats(), schedule=o) for o in schedules.efficient(p)[0]]
    return [(Configuration(p, c.order, single), c) for c in best if c.restrictions != single]


def restriction_speedup(g: Graph, p: Pattern) -> tuple[float, float, int]:
    """Over orders where the model's set differs from the single set: mean and maximum gain in loop work, and how many."""
    meter, pairs = LoopWork(g), set_pairs(g, p)
    top, most = speedup([meter.of(a) for a, _ in pairs], [max(1, meter.of(b)) for _, b in pairs])
    return (top, most, len(pairs)) if pairs else (1.0, 1.0, 0)


def schedule_pair(g: Graph, p: Pattern) -> tuple[Configuration, Configuration]:
    """With the single set for both: the order a random-graph estimate picks, and ours."""
    single, s = symmetry.closure(symmetry.orbit_restrictions(p)), g.stats()
    flat = cost_model.GraphStats(s.n_vertices, s.n_edges, int((2 * s.n_edges) ** 3 / max(1, s.n_vertices) ** 3 / 6))
    return planner.choose(p, flat, restrictions=single, phases=1), planner.choose(p, s, restrictions=single)


def schedule_speedup(g: Graph, p: Pattern) -> float:
    """Loop work of the first of schedule_pair() against the second."""
    meter, (other, ours) = LoopWork(g), schedule_pair(g, p)
    return meter.of(other) / max(1, meter.of(ours))


def iep_speedup(g: Graph, p: Pattern, timeout: float | None = None) -> tuple[Timed, Timed]:
    """The same configuration, enumerated and by inclusion-exclusion."""
    c = planner.choose_iep(p, g.stats())
    return (
        timed(g, lambda: api.count(g, p, Configuration(p, c.order, c.restrictions), method="enumerate"), timeout),
        timed(g, lambda: api.count(g, p, c, method="iep"), timeout),
    )


def loop_rows(g: Graph, c: Configuration) -> list[tuple[str, int, float]]:
    """(vertex, rows, rows the model expects) of each loop."""
    meter, rules = LoopWork(g), symmetry.closure(c.restrictions)
    sizes = cost_model.loop_sizes(c.order, c.pattern, g.stats())
    probs = cost_model.filter_probs(c.order, c.pattern, rules)
    out, expected = [], 1.0
    for i, v in enumerate(c.order):
        expected *= sizes[i] * (1 - probs[i])
        out.append((c.pattern.names[v], meter.prefix_rows(c.pattern, frozenset(c.order[: i + 1]), rules), expected))
    return out


def scale(g: Graph, p: Pattern, tasks: list[int]) -> list[tuple[int, float, float]]:
    """(tasks at once, seconds, speed-up over the first): the replicated executor with its prefixes in so many partitions."""
    from .operators import executor

    out: list[tuple[int, float, float]] = []
    for k in tasks:
        t = timed(g, lambda k=k: executor.replicated_count(g, p, partitions=k))
        out.append((k, t.seconds, out[0][1] / t.seconds if out else 1.0))
    return out
