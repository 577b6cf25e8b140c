"""Pattern symmetry: automorphisms, and sets of id inequalities that keep one copy of each subgraph.

An inequality (hi, lo) demands id(hi) > id(lo). The n! possible orders of n ids are kept as one bit each of a Python
integer, so that "some order satisfies these inequalities" - which is to say, they form no cycle - is one AND.
"""

from __future__ import annotations

from functools import cache
from itertools import permutations
from math import factorial

import numpy as np

from .patterns import Pattern

Pair = tuple[int, int]
Restrictions = frozenset[Pair]


@cache
def automorphisms(p: Pattern) -> tuple[tuple[int, ...], ...]:
    """All permutations that keep edges, directions and labels, in lexicographic order."""
    edges = {e: lab for e, lab in zip(p.edges, p.elabels or [None] * len(p.edges), strict=True)}
    if not p.directed:
        edges |= {(b, a): lab for (a, b), lab in edges.items()}
    kind = [(len(p.around[v]), (p.vlabels or [None] * p.n)[v]) for v in range(p.n)]
    found: list[tuple[int, ...]] = []

    def extend(image: list[int]) -> None:
        v = len(image)
        if v == p.n:
            found.append(tuple(image))
            return
        for x in range(p.n):
            if x not in image and kind[x] == kind[v] and all(
                edges.get((u, v), 0) == edges.get((image[u], x), 0) and edges.get((v, u), 0) == edges.get((x, image[u]), 0) for u in range(v)
            ):
                extend([*image, x])

    extend([])
    return tuple(found)


def cycles(perm: tuple[int, ...]) -> tuple[tuple[int, ...], ...]:
    """Disjoint cycles, fixed points included, each from its smallest member."""
    seen: set[int] = set()
    out = []
    for v in range(len(perm)):
        if v not in seen:
            ring = [v]
            while perm[ring[-1]] != v:
                ring.append(perm[ring[-1]])
            seen.update(ring)
            out.append(tuple(ring))
    return tuple(out)


def swaps(perm: tuple[int, ...]) -> list[Pair]:
    """The 2-cycles. A fixed point is not one, though it too is its own double image."""
    return [c for c in cycles(perm) if len(c) == 2]


def as_transpositions(cycle: tuple[int, ...]) -> list[Pair]:
    """A k-cycle as k - 1 swaps, the last to be applied first."""
    return [(cycle[0], x) for x in reversed(cycle[1:])]


class Orders:
    """The n! orders of n ids as bits."""

    def __init__(self, n: int):
        self.n, self.count = n, factorial(n)
        self.ranks = np.array(list(permutations(range(n))), np.int8)
        self.all = (1 << self.count) - 1
        self.above = {}
        for a in range(n):
            for b in range(n):
                if a != b:
                    bits = np.packbits(self.ranks[:, a] > self.ranks[:, b], bitorder="little")
                    self.above[a, b] = int.from_bytes(bits.tobytes(), "little")

    def mask(self, restrictions) -> int:
        m = self.all
        for pair in restrictions:
            m &= self.above[pair]
        return m

    def holds(self, restrictions) -> np.ndarray:
        """One boolean an order."""
        ok = np.ones(self.count, bool)
        for a, b in restrictions:
            ok &= self.ranks[:, a] > self.ranks[:, b]
        return ok


@cache
def orders(n: int) -> Orders:
    return Orders(n)


def image(perm: tuple[int, ...], restrictions) -> Restrictions:
    return frozenset((perm[a], perm[b]) for a, b in restrictions)


def survives(perm: tuple[int, ...], restrictions) -> bool:
    """Whether inequalities and their image can hold together: the permutation is not yet ruled out."""
    n = len(perm)
    return bool(orders(n).mask(restrictions) & orders(n).mask(image(perm, restrictions)))


def closure(restrictions) -> Restrictions:
    """With all inequalities implied by transitivity."""
    out = set(restrictions)
    while True:
        more = {(a, d) for a, b in out for c, d in out if b == c} - out
        if not more:
            return frozenset(out)
        out |= more


def validate(p: Pattern, restrictions) -> bool:
    """Exactly one in |Aut| orders is kept, as counting on the complete graph of n vertices would show."""
    return orders(p.n).mask(restrictions).bit_count() * len(automorphisms(p)) == factorial(p.n)


def orbit_restrictions(p: Pattern) -> Restrictions:
    """One complete set: fix a vertex, put it above the rest of its orbit, go on with what leaves it fixed."""
    group, out = list(automorphisms(p)), set()
    for v in range(p.n):
        orbit = {g[v] for g in group} - {v}
        out |= {(v, w) for w in orbit}
        group = [g for g in group if g[v] == v]
    return frozenset(out)


def twin_restrictions(p: Pattern) -> Restrictions:
    """Orders only vertices with the same neighbours, themselves aside; may be incomplete."""
    out = set()
    for a in range(p.n):
        for b in range(a + 1, p.n):
            if p.around[a] - {b} == p.around[b] - {a} and not p.directed and (not p.vlabels or p.vlabels[a] == p.vlabels[b]):
                out.add((a, b))
    return frozenset(out)


@cache
def restriction_sets(p: Pattern, max_states: int = 400_000) -> tuple[Restrictions, ...]:
    """All complete sets reachable by adding swaps of permutations that survive, in either direction.

    A set that keeps fewer orders than n! / |Aut| can only lose more and is given up. Cliques of five or more have
    one set per total order: the chains are given outright. Where nothing is found, and where the search is cut at
    ``max_states`` sets, the orbit set is added.
    """
    group, n = automorphisms(p), p.n
    if len(group) == 1:
        return (frozenset(),)
    table = orders(n)
    target = table.count // len(group)
    if target == 1 and n >= 5:
        return tuple(sorted((frozenset(zip(o, o[1:], strict=False)) for o in permutations(range(n))), key=sorted))
    identity = tuple(range(n))
    moves = [g for g in group if g != identity]
    seen: set[Restrictions] = set()
    valid: set[Restrictions] = set()
    stack: list[tuple[Restrictions, int, tuple[tuple[tuple[int, ...], int], ...]]] = [(frozenset(), table.all, tuple((g, table.all) for g in moves))]
    while stack and len(seen) < max_states:
        chosen, mask, alive = stack.pop()
        if not alive:
            if mask.bit_count() == target:
                valid.add(chosen)
            continue
        for a, b in {pair for g, _ in alive for s in swaps(g) for pair in (s, s[::-1])}:
            bigger = chosen | {(a, b)}
            if bigger in seen:
                continue
            seen.add(bigger)
            kept = mask & table.above[a, b]
            if kept.bit_count() < target:
                continue
            left = []
            for g, own in alive:
                own &= table.above[g[a], g[b]]
                if own & kept:
                    left.append((g, own))
            stack.append((bigger, kept, tuple(left)))
    if not valid or stack:
        valid.add(orbit_restrictions(p))
    return tuple(sorted(valid, key=lambda s: (len(s), sorted(s))))


def overcount(p: Pattern, restrictions) -> np.ndarray:
    """How often each order's subgraph is kept: the permutations that map the order to one that satisfies the set."""
    table = orders(p.n)
    return sum((table.holds(image(g, restrictions)).astype(np.int64) for g in automorphisms(p)), np.zeros(table.count, np.int64))


def report(p: Pattern) -> dict:
    return {"automorphisms": len(automorphisms(p)), "restriction_sets": len(restriction_sets(p)), "orders_kept": orders(p.n).count // len(automorphisms(p))}
