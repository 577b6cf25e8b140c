"""Counting tuples of pairwise different members of sets by inclusion-exclusion over set sizes."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from itertools import combinations
from math import factorial, prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.compiler import Operand, array_name, lists_with, size_name
from ..plans.planner import Configuration


def partitions(items: tuple[int, ...]) -> list[list[tuple[int, ...]]]:
    """All set partitions; Bell(k) of them."""
    if not items:
        return [[]]
    first, rest = items[0], items[1:]
    out = []
    for p in partitions(rest):
        out.append([(first,), *p])
        out += [[*p[:i], (first, *p[i]), *p[i + 1 :]] for i in range(len(p))]
    return out


def components(k: int, pairs) -> list[tuple[int, ...]]:
    """Connected components of the graph on 0..k-1 with these edges."""
    own = list(range(k))
    for a, b in pairs:
        x, y = own[a], own[b]
        own = [min(x, y) if o in (x, y) else o for o in own]
    return [tuple(i for i in range(k) if own[i] == r) for r in sorted(set(own))]


def terms(k: int, form: str = "partitions") -> list[tuple[int, tuple[tuple[int, ...], ...]]]:
    """(coefficient, blocks) whose blocks' intersection sizes are to be multiplied.

    "pairs": one term for each subset of the k(k-1)/2 pairs that may coincide, 2**(k(k-1)/2) in all.
    "partitions": those with equal blocks added up; a block of b gives (-1)**(b-1) (b-1)!.
    """
    if form == "pairs":
        every = list(combinations(range(k), 2))
        return [((-1) ** r, tuple(components(k, s))) for r in range(len(every) + 1) for s in combinations(every, r)]
    return [(prod((-1) ** (len(b) - 1) * factorial(len(b) - 1) for b in p), tuple(tuple(sorted(b)) for b in p)) for p in partitions(tuple(range(k)))]


def term_cardinality(k: int, pairs, sets: list[set]) -> int:
    """Tuples in which each of the pairs coincides: product over components of their intersections' sizes."""
    return prod(len(set.intersection(*(sets[i] for i in c))) for c in components(k, pairs))


def count_python(sets: list[set], form: str = "partitions") -> int:
    """The same for Python sets: the number of tuples of different members."""
    return sum(c * prod(len(set.intersection(*(sets[i] for i in b))) for b in blocks) for c, blocks in terms(len(sets), form))


@dataclass(frozen=True)
class Block:
    """The shared candidates of some of the last loops, and which bound vertices are among them."""

    operands: frozenset[Operand]
    arrays: tuple[tuple[Operand, ...], ...]  # kept arrays whose intersection it is; none where a list's length tells its size
    inside: int  # bound vertices that the pattern's edges put in it
    probed: tuple[int, ...]  # bound vertices that may be in it


def blocks(c: Configuration, k: int) -> dict[tuple[int, ...], Block]:
    """For each set of the last k loops (numbered from 0) what is needed to know its size.

    A loop whose lists are all among another's adds nothing to an intersection with it. A vertex is in none of its own
    lists, and in the lists of vertices it is adjacent to in the pattern; only of others it must be looked.
    """
    p, outer = c.pattern, c.order[: c.pattern.n - k]
    candidates = [tuple(x for u in outer for x in lists_with(p, u, v)) for v in c.order[p.n - k :]]
    found = {}
    for q in range(1, k + 1):
        for own in combinations(range(k), q):
            lists = frozenset(x for i in own for x in candidates[i])
            exact = next((s for s in candidates if frozenset(s) == lists), None)
            parts = dict.fromkeys(candidates[i] for i in own)
            least = tuple(s for s in parts if not any(set(s) < set(t) for t in parts))
            others = [u for u in outer if all(x[0] != u for x in lists)]
            probed = tuple(u for u in others if any(x not in lists_with(p, x[0], u) for x in lists))
            arrays = (exact,) if exact else least
            found[own] = Block(lists, () if len(lists) == 1 and not probed else arrays, len(others) - len(probed), probed)
    return found


def kept(c: Configuration, k: int, form: str = "partitions") -> tuple[tuple[tuple[Operand, ...], ...], tuple[Operand, ...]]:
    """(arrays, lists of which the length is enough) that the last k loops need from the loops before."""
    used = {b for _, bs in terms(k, form) for b in bs}
    every = [b for own, b in blocks(c, k).items() if own in used]
    return tuple(dict.fromkeys(a for b in every for a in b.arrays)), tuple(dict.fromkeys(x for b in every if not b.arrays for x in b.operands))


def count_steps(df: DataFrame, c: Configuration, k: int, form: str = "partitions", wide: bool = False) -> DataFrame:
    """One row per row of ``df``, ``tuples``: how many tuples of different ids the last k loops would bind.

    df: the loops before, with the arrays and lengths of kept(). Three projections: the intersections, their sizes without
    bound ids, the sum of products. Each intersection is taken once for each different set of lists, since a projection
    that others use more than once is not inlined.
    """
    kind, names = "decimal(38,0)" if wide else "long", c.pattern.names
    every = blocks(c, k)
    used = {b for _, bs in terms(k, form) for b in bs}
    own = {every[b].operands: every[b] for b in sorted(used)}
    label = {lists: f"x_{i}" for i, lists in enumerate(own)}
    made = {lists: reduce(F.array_intersect, [F.col(array_name(c, a)) for a in b.arrays]).alias(label[lists]) for lists, b in own.items() if b.arrays}
    lengths = [size_name(c, next(iter(lists))) for lists, b in own.items() if not b.arrays]
    df = df.select(*(names[v] for v in c.order[: c.pattern.n - k]), *lengths, *made.values())
    sizes = []
    for lists, b in own.items():
        size = (F.size(label[lists]) if b.arrays else F.col(size_name(c, next(iter(lists))))) - F.lit(b.inside)
        for u in b.probed:
            size = size - F.array_contains(label[lists], F.col(names[u])).cast("int")
        sizes.append(size.cast(kind).alias(label[lists]))
    df = df.select(*sizes)
    total = F.lit(0).cast(kind)
    for sign, bs in terms(k, form):
        total = total + F.lit(sign).cast(kind) * reduce(lambda a, b: a * b, [F.col(label[every[b].operands]) for b in bs])
    return df.select(total.cast(kind).alias("tuples"))
