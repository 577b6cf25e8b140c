"""Closed-form cost of a configuration from three statistics of the data graph."""

from __future__ import annotations

from dataclasses import dataclass

from .patterns import Pattern
from .schedules import Order
from .symmetry import closure, orders


@dataclass(frozen=True)
class GraphStats:
    """n_triangles counts distinct triangles; ``triangle_unit`` says how the model reads it ("ordered": six each)."""

    n_vertices: int
    n_edges: int
    n_triangles: int
    triangle_unit: str = "ordered"

    @property
    def triangles(self) -> int:
        return self.n_triangles * (6 if self.triangle_unit == "ordered" else 1)

    @property
    def p1(self) -> float:
        """Probability that two vertices are adjacent."""
        return 2 * self.n_edges / self.n_vertices**2 if self.n_vertices else 0.0

    @property
    def p2(self) -> float:
        """Probability that two neighbours of a vertex are adjacent."""
        return self.triangles * self.n_vertices / (2 * self.n_edges) ** 2 if self.n_edges else 0.0


def card(q: int, stats: GraphStats) -> float:
    """Expected size of an intersection of q neighbourhoods; all vertices for q = 0."""
    return float(stats.n_vertices) if q == 0 else stats.n_vertices * stats.p1 * stats.p2 ** (q - 1)


def operands(order: Order, p: Pattern) -> list[Order]:
    """For each loop, the earlier vertices whose neighbourhoods its candidates are in, in order of binding."""
    return [tuple(u for u in order[:i] if p.adjacent(u, v)) for i, v in enumerate(order)]


def temporaries(order: Order, p: Pattern) -> list[list[Order]]:
    """For each loop, the intersections that can be taken once its vertex is bound. Later loops that start with the
    same vertices share one."""
    sets = operands(order, p)
    made: dict[Order, None] = {}
    for s in sets:
        for q in range(2, len(s) + 1):
            made.setdefault(s[:q])
    return [[t for t in made if t[-1] == v] for v in order]


def loop_sizes(order: Order, p: Pattern, stats: GraphStats) -> list[float]:
    return [card(len(s), stats) for s in operands(order, p)]


def intersect_costs(order: Order, p: Pattern, stats: GraphStats) -> list[float]:
    return [sum(card(len(t) - 1, stats) + card(1, stats) for t in ts) for ts in temporaries(order, p)]


def filter_probs(order: Order, p: Pattern, restrictions, filter_loop: str = "later") -> list[float]:
    """Share of the magnitude orders still possible that each loop's inequalities remove.

    filter_loop: "later" tests an inequality where its second vertex is bound, "printed" one loop before.
    """
    table = orders(p.n)
    at = {v: i for i, v in enumerate(order)}
    mask, out = table.all, []
    for i in range(p.n):
        before = mask.bit_count()
        for a, b in restrictions:
            where = max(at[a], at[b]) - (filter_loop == "printed")
            if where == i:
                mask &= table.above[a, b]
        out.append(1 - mask.bit_count() / before if before else 0.0)
    return out


def cost(order: Order, p: Pattern, restrictions, stats: GraphStats, filter_loop: str = "later") -> float:
    return costs(order, p, restrictions, stats, filter_loop)[0]


def costs(order: Order, p: Pattern, restrictions, stats: GraphStats, filter_loop: str = "later") -> list[float]:
    """Cost of each loop with all that it encloses, the outermost first."""
    sizes, work = loop_sizes(order, p, stats), intersect_costs(order, p, stats)
    f = filter_probs(order, p, closure(restrictions), filter_loop)
    out = [sizes[-1] * (1 - f[-1])]
    for i in range(p.n - 2, -1, -1):
        out.append(sizes[i] * (1 - f[i]) * (work[i] + out[-1]))
    return out[::-1]


def suffix_cost(order: Order, p: Pattern, restrictions, stats: GraphStats, k: int) -> float:
    """Cost when the last k loops are replaced by inclusion-exclusion: their intersections instead of their loops."""
    sizes, work = loop_sizes(order, p, stats), intersect_costs(order, p, stats)
    outer = [r for r in closure(restrictions) if not set(r) & set(order[p.n - k :])]
    f = filter_probs(order, p, outer)
    total = sum(sizes[p.n - k :]) * (1 if k == 1 else k)
    for i in range(p.n - k - 1, -1, -1):
        total = sizes[i] * (1 - f[i]) * (work[i] + total)
    return total
