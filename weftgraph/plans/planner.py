"""Choice of a configuration: a vertex order, a restriction set and how many loops inclusion-exclusion replaces."""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from functools import cache

from . import cost_model, schedules, symmetry
from .patterns import Pattern
from .schedules import Order
from .symmetry import Restrictions


@dataclass(frozen=True)
class Configuration:
    pattern: Pattern
    order: Order
    restrictions: Restrictions
    cost: float = float("nan")
    iep_k: int = 0
    outer: Restrictions = frozenset()
    divisor: int = 1

    def names(self) -> tuple[list[str], list[str]]:
        p = self.pattern
        return [p.names[v] for v in self.order], [f"{p.names[a]}>{p.names[b]}" for a, b in sorted(self.restrictions)]


@cache
def distinct_sets(p: Pattern) -> tuple[Restrictions, ...]:
    """Restriction sets that differ in what they imply; each one closed."""
    return tuple(dict.fromkeys(symmetry.closure(s) for s in symmetry.restriction_sets(p)))


def rank(p: Pattern, stats: cost_model.GraphStats, schedule: Order | None = None, restrictions: Restrictions | None = None, phases: int = 2, filter_loop: str = "later") -> list[Configuration]:
    """All configurations, cheapest first. Ties: fewer intersections, earlier inequalities, then by order."""
    orders = [schedule] if schedule else schedules.efficient(p, phases)[0]
    sets = [symmetry.closure(restrictions)] if restrictions is not None else distinct_sets(p)
    out = []
    for o in orders:
        at = {v: i for i, v in enumerate(o)}
        work = sum(len(t) for t in cost_model.temporaries(o, p))
        for s in sets:
            c = cost_model.cost(o, p, s, stats, filter_loop)
            out.append((c, work, sum(max(at[a], at[b]) for a, b in s), o, sorted(s), Configuration(p, o, s, c)))
    return [x[-1] for x in sorted(out, key=lambda x: x[:-1])]


def choose(p: Pattern, stats: cost_model.GraphStats, schedule: Order | None = None, restrictions: Restrictions | None = None, phases: int = 2) -> Configuration:
    return rank(p, stats, schedule, restrictions, phases)[0]


def outer_restrictions(c: Configuration, k: int) -> Restrictions:
    """Inequalities among the vertices bound by loops, implied ones included."""
    inner = set(c.order[c.pattern.n - k :])
    return frozenset(r for r in symmetry.closure(c.restrictions) if not set(r) & inner)


def divisor_paper(p: Pattern, outer: Restrictions) -> int:
    """Permutations that the outer inequalities leave possible."""
    return sum(symmetry.survives(g, outer) for g in symmetry.automorphisms(p))


def divisor_exact(p: Pattern, outer: Restrictions) -> int | None:
    """How often each subgraph is counted under the outer inequalities; None where that depends on its ids."""
    times = symmetry.overcount(p, outer)
    return int(times[0]) if times.min() == times.max() else None


@cache
def uniform_outer(p: Pattern, outer: Restrictions) -> tuple[Restrictions, int]:
    """Drop as few inequalities as needed until every subgraph is counted equally often."""
    queue, seen = [outer], {outer}
    while queue:
        s = queue.pop(0)
        if (d := divisor_exact(p, s)) is not None:
            return s, d
        for r in sorted(s):
            if (t := s - {r}) not in seen:
                seen.add(t)
                queue.append(t)
    raise AssertionError("no inequality at all counts each subgraph |Aut| times")


def with_iep(c: Configuration, k: int | None = None) -> Configuration:
    """The same order and set, with the last k loops (all independent ones by default) left to inclusion-exclusion."""
    k = min(schedules.suffix_size(c.order, c.pattern), c.pattern.n - 1) if k is None else k
    outer, divisor = uniform_outer(c.pattern, outer_restrictions(c, k))
    return Configuration(c.pattern, c.order, c.restrictions, c.cost, k, outer, divisor)


def choose_iep(p: Pattern, stats: cost_model.GraphStats) -> Configuration:
    """Rank by the cost of the outer loops and the intersections that remain, under usable outer inequalities."""
    best = None
    for o in schedules.efficient(p)[0]:
        k = min(schedules.suffix_size(o, p), p.n - 1)
        tried = {}
        for s in distinct_sets(p):
            outer = outer_restrictions(Configuration(p, o, s), k)
            if outer in tried:
                continue
            usable, divisor = uniform_outer(p, outer)
            tried[outer] = None
            c = cost_model.suffix_cost(o, p, usable, stats, k)
            if best is None or (c, o) < (best.cost, best.order):
                best = Configuration(p, o, s, c, k, usable, divisor)
    return best


@dataclass
class Prepared:
    configuration: Configuration
    ranked: int
    timings: dict[str, float] = field(default_factory=dict)


def prepare(p: Pattern, stats: cost_model.GraphStats) -> Prepared:
    """The whole preparation, step by step and timed."""
    t: dict[str, float] = {}

    def timed(name, f):
        began = time.perf_counter()
        out = f()
        t[name] = time.perf_counter() - began
        return out

    for f in (symmetry.automorphisms, symmetry.restriction_sets, symmetry.orders, schedules.efficient, schedules.independence_number, distinct_sets):
        f.cache_clear()
    timed("automorphisms", lambda: symmetry.automorphisms(p))
    timed("restriction_sets", lambda: symmetry.restriction_sets(p))
    timed("schedules", lambda: schedules.efficient(p))
    ranked = timed("ranking", lambda: rank(p, stats))

    def generate():
        """The loop plan, its SQL text and the suffix's blocks: what is made for the engine to run."""
        from ..operators import iep
        from . import compiler, sql

        c = with_iep(ranked[0])
        return compiler.loop_plan(c), iep.blocks(c, c.iep_k), sql.steps(p, "SELECT src, dst FROM edges", c.restrictions, order=c.order)

    timed("generation", generate)
    return Prepared(ranked[0], len(ranked), t)
