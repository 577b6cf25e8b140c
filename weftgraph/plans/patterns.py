"""Patterns: small graphs to look for, and the catalogue of those the experiments use."""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import cached_property
from itertools import combinations, permutations


@dataclass(frozen=True)
class Pattern:
    """A connected simple graph on a few named vertices; direction and labels are optional.

    edges hold index pairs, ordered (low, high) unless ``directed``. vlabels and elabels name a required label per
    vertex or per edge, None for any.
    """

    names: tuple[str, ...]
    edges: tuple[tuple[int, int], ...]
    directed: bool = False
    vlabels: tuple[str | None, ...] | None = None
    elabels: tuple[str | None, ...] | None = None

    def __post_init__(self):
        n = len(self.names)
        if n < 2 or len(set(self.names)) != n:
            raise ValueError("a pattern needs two vertices or more, with different names")
        if len(set(self.edges)) != len(self.edges) or any(a == b or not 0 <= min(a, b) <= max(a, b) < n for a, b in self.edges):
            raise ValueError("a pattern has no loops and no repeated edges")
        reached, rest = {0}, True
        while rest:
            rest = {b for a in reached for b in self.around[a]} - reached
            reached |= rest
        if len(reached) != n:
            raise ValueError("a pattern must be connected")

    @property
    def n(self) -> int:
        return len(self.names)

    @cached_property
    def around(self) -> tuple[frozenset[int], ...]:
        """Neighbours of each vertex, direction aside."""
        return tuple(frozenset({b for a, b in self.edges if a == v} | {a for a, b in self.edges if b == v}) for v in range(len(self.names)))

    @classmethod
    def parse(cls, text: str, vlabels: dict[str, str] | None = None, elabels: dict[str, str] | None = None) -> Pattern:
        """``"A-B, B-C"``, or ``"A>B"`` for directed edges; vertices are numbered by name."""
        parts = [p.strip() for p in text.split(",") if p.strip()]
        found = [re.fullmatch(r"(\w+)\s*(-|>)\s*(\w+)", p) for p in parts]
        if not parts or not all(found):
            raise ValueError(f"not a list of edges: {text!r}")
        signs = {m[2] for m in found}
        if len(signs) > 1:
            raise ValueError("either all edges are directed or none")
        names = tuple(sorted({x for m in found for x in (m[1], m[3])}))
        at = {x: i for i, x in enumerate(names)}
        directed = signs == {">"}
        edges = [(at[m[1]], at[m[3]]) if directed else tuple(sorted((at[m[1]], at[m[3]]))) for m in found]
        marks = {e: (elabels or {}).get(p.replace(" ", "")) for e, p in zip(edges, parts, strict=True)}
        edges = tuple(sorted(edges))
        return cls(names, edges, directed, tuple(vlabels.get(x) for x in names) if vlabels else None, tuple(marks[e] for e in edges) if elabels else None)

    def adjacent(self, a: int, b: int) -> bool:
        return b in self.around[a]

    def text(self) -> str:
        return ", ".join(f"{self.names[a]}{'>' if self.directed else '-'}{self.names[b]}" for a, b in self.edges)


def clique(n: int) -> Pattern:
    names = tuple("ABCDEFGH"[:n])
    return Pattern(names, tuple(combinations(range(n), 2)))


def connected_shapes(n: int) -> list[Pattern]:
    """All connected graphs on n vertices up to isomorphism: 1, 2, 6 and 21 for n = 2 to 5."""
    pairs = list(combinations(range(n), 2))
    seen: set[frozenset] = set()
    out = []
    for size in range(n - 1, len(pairs) + 1):
        for edges in combinations(pairs, size):
            key = min(tuple(sorted(tuple(sorted((p[a], p[b]))) for a, b in edges)) for p in permutations(range(n)))
            if frozenset(key) in seen:
                continue
            try:
                out.append(Pattern(tuple("ABCDEFGH"[:n]), key))
            except ValueError:
                continue
            seen.add(frozenset(key))
    return out


#: Shapes of the experiments: w1 to w6 stand in for six evaluation patterns.
CATALOGUE = {
    "edge": "A-B",
    "wedge": "A-B, A-C",
    "triangle": "A-B, A-C, B-C",
    "rectangle": "A-B, B-C, C-D, A-D",
    "tailed": "A-B, A-C, B-C, A-D",
    "diamond": "A-B, A-C, B-C, A-D, B-D",
    "star3": "A-B, A-C, A-D",
    "path4": "A-B, B-C, C-D",
    "k4": clique(4).text(),
    "k5": clique(5).text(),
    "c5": "A-B, B-C, C-D, D-E, A-E",
    "c6": "A-B, B-C, C-D, D-E, E-F, A-F",
    "prism": "A-B, B-C, A-C, D-E, E-F, D-F, A-D, B-E, C-F",
    "w1": "A-B, A-C, B-D, C-D, A-E, B-E",
    "w2": "A-B, A-C, B-C, A-D, B-D, B-E, C-E, A-F, C-F",
    "w3": "A-B, A-C, B-C, A-D, B-D, A-E, B-E, A-F, C-F",
    "w4": "A-B, B-C, C-D, A-D, A-E, B-E, C-F, D-F",
    "w5": "A-B, B-C, C-D, D-E, E-F, F-G, A-C, B-D, C-E, D-F, E-G",
    "w6": "A-B, A-C, A-D, A-E, A-F, A-G, B-C, C-D, D-E, E-F, F-G, B-G",
}
WORKLOAD = ["w1", "w2", "w3", "w4", "w5", "w6"]


def named(name: str) -> Pattern:
    return Pattern.parse(CATALOGUE[name])
