"""Vertex orders and the two structural filters on them."""

from __future__ import annotations

from functools import cache
from itertools import combinations, permutations

from .patterns import Pattern

Order = tuple[int, ...]


def all_orders(p: Pattern) -> list[Order]:
    return list(permutations(range(p.n)))


def is_connected_prefix(order: Order, p: Pattern) -> bool:
    return all(p.around[v] & set(order[:i]) for i, v in enumerate(order) if i)


def connected_prefix(orders: list[Order], p: Pattern) -> list[Order]:
    """Phase 1: every vertex after the first has an earlier neighbour, so no loop ranges over all vertices."""
    return [o for o in orders if is_connected_prefix(o, p)]


def independent(vertices, p: Pattern) -> bool:
    return not any(p.adjacent(a, b) for a, b in combinations(vertices, 2))


@cache
def independence_number(p: Pattern) -> int:
    return max(k for k in range(1, p.n + 1) if any(independent(c, p) for c in combinations(range(p.n), k)))


def independent_suffix(orders: list[Order], p: Pattern, k: int | None = None) -> list[Order]:
    """Phase 2: the last k vertices have no edges among them, so all intersections are done before their loops."""
    k = independence_number(p) if k is None else k
    return [o for o in orders if independent(o[p.n - k :], p)]


@cache
def efficient(p: Pattern, phases: int = 2) -> tuple[tuple[Order, ...], int]:
    """(orders, usable k). Where no order passes both phases for k, the largest smaller k that leaves some is used."""
    found = all_orders(p)
    if phases == 0:
        return tuple(found), 0
    found = connected_prefix(found, p)
    if phases == 1:
        return tuple(found), 0
    for k in range(independence_number(p), 0, -1):
        if kept := independent_suffix(found, p, k):
            return tuple(kept), k
    return tuple(found), 0


def suffix_size(order: Order, p: Pattern) -> int:
    """The longest run of pairwise non-adjacent vertices at the end of an order."""
    k = 1
    while k < p.n and independent(order[p.n - k - 1 :], p):
        k += 1
    return k


def report(p: Pattern) -> dict:
    orders = all_orders(p)
    one = connected_prefix(orders, p)
    return {"all": len(orders), "phase1": len(one), "phase2": len(efficient(p)[0]), "k": independence_number(p), "usable_k": efficient(p)[1]}
