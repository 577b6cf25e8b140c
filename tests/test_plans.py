"""Pattern side: symmetry, schedules, cost model, choice of configuration, divisors."""

from itertools import permutations
from math import factorial

import pytest

from weftgraph.operators import iep
from weftgraph.plans import cost_model, planner, schedules, symmetry
from weftgraph.plans.patterns import CATALOGUE, Pattern, clique, connected_shapes, named

STATS = cost_model.GraphStats(1997, 13385, 6424)

EXPECTED = {  # automorphisms, restriction sets, k, usable k, phase 1, phase 2
    "triangle": (6, 12, 1, 1, 6, 6), "rectangle": (8, 32, 2, 1, 16, 16), "diamond": (4, 4, 2, 2, 20, 4), "tailed": (2, 2, 2, 2, 14, 8), "star3": (6, 12, 3, 3, 12, 6),
    "path4": (2, 4, 2, 2, 8, 4), "k4": (24, 192, 1, 1, 24, 24), "c5": (10, 80, 2, 1, 40, 40), "c6": (12, 96, 3, 1, 96, 96), "prism": (12, 96, 2, 2, 360, 96),
    "w1": (2, 4, 2, 2, 60, 16), "w2": (6, 48, 3, 3, 336, 36), "w3": (2, 2, 3, 3, 376, 60), "w4": (4, 16, 2, 2, 240, 96), "w5": (2, 6, 3, 3, 1384, 48), "w6": (12, 96, 3, 3, 2160, 144),
}


@pytest.mark.parametrize("name", EXPECTED)
def test_pattern_table(name):
    p, s = named(name), schedules.report(named(name))
    assert (len(symmetry.automorphisms(p)), len(symmetry.restriction_sets(p)), s["k"], s["usable_k"], s["phase1"], s["phase2"]) == EXPECTED[name]
    assert all(symmetry.validate(p, r) for r in symmetry.restriction_sets(p)) and symmetry.validate(p, symmetry.orbit_restrictions(p))
    assert all(a != b for r in symmetry.restriction_sets(p) for a, b in r)


def test_patterns_are_checked():
    for bad in ("A-B, C-D", "A-A", "A-B, B-A", "A", "A>B, B-C"):
        with pytest.raises(ValueError):
            Pattern.parse(bad)
    assert [len(connected_shapes(n)) for n in (2, 3, 4, 5)] == [1, 2, 6, 21]
    assert len(symmetry.automorphisms(clique(7))) == 5040 and len(symmetry.restriction_sets(clique(7))) == factorial(7)


def test_rectangle_by_hand():
    group = symmetry.automorphisms(named("rectangle"))
    forms = {tuple(c for c in symmetry.cycles(g) if len(c) > 1) for g in group}
    assert forms == {(), ((1, 3),), ((0, 2),), ((0, 1), (2, 3)), ((0, 3), (1, 2)), ((0, 2), (1, 3)), ((0, 1, 2, 3),), ((0, 3, 2, 1),)}
    turn = next(g for g in group if symmetry.cycles(g) == ((0, 1, 2, 3),))
    assert symmetry.survives(turn, {(1, 3)}) and not symmetry.survives(turn, {(1, 3), (0, 2)})
    for g in group:
        for c in symmetry.cycles(g):
            made = list(range(4))
            for a, b in reversed(symmetry.as_transpositions(c)):
                made = [b if x == a else a if x == b else x for x in made]
            assert all(made[v] == g[v] for v in c)


def test_directed_ring_has_no_swap():
    ring = Pattern.parse("A>B, B>C, C>A")
    assert len(symmetry.automorphisms(ring)) == 3 and not any(symmetry.swaps(g) for g in symmetry.automorphisms(ring))
    assert symmetry.restriction_sets(ring) == (symmetry.orbit_restrictions(ring),) and symmetry.validate(ring, symmetry.orbit_restrictions(ring))


def test_cost_of_the_house():
    p = named("w1")
    got = cost_model.costs((0, 1, 2, 3, 4), p, {(0, 1)}, STATS)
    for a, b in zip(got, [5_541_308.99, 2_774.816718, 387.183732, 2.073084, 1.439821], strict=True):
        assert a == pytest.approx(b, rel=1e-6)
    assert (STATS.p1, STATS.p2) == (pytest.approx(0.0067126, abs=1e-7), pytest.approx(0.1074084, abs=1e-7))
    assert cost_model.filter_probs((0, 1, 2, 3, 4), p, {(0, 1)}) == [0, 0.5, 0, 0, 0]
    assert cost_model.filter_probs((0, 1, 2, 3, 4), p, {(0, 1)}, "printed")[0] == 0.5
    assert cost_model.card(2, cost_model.GraphStats(1997, 13385, 6424, "distinct")) == pytest.approx(0.2400, abs=1e-4)
    assert cost_model.card(2, cost_model.GraphStats(10, 20, 0)) == 0


@pytest.mark.parametrize("name", EXPECTED)
def test_filters_leave_one_copy(name):
    p = named(name)
    for c in planner.rank(p, STATS)[:5]:
        kept = 1.0
        for f in cost_model.filter_probs(c.order, p, c.restrictions):
            kept *= 1 - f
        assert kept * len(symmetry.automorphisms(p)) == pytest.approx(1)


def test_divisors():
    tri, w2, w4 = named("triangle"), named("w2"), named("w4")
    assert (planner.divisor_paper(tri, frozenset({(1, 2)})), planner.divisor_exact(tri, frozenset({(1, 2)}))) == (5, 3)
    assert (planner.divisor_paper(w2, frozenset({(2, 0)})), planner.divisor_exact(w2, frozenset({(2, 0)}))) == (5, 3)
    assert (planner.divisor_paper(w4, frozenset({(0, 1)})), planner.divisor_exact(w4, frozenset({(0, 1)}))) == (3, 2)
    rect = named("rectangle")
    uneven = frozenset({(1, 2), (1, 3)})
    assert planner.divisor_paper(rect, uneven) == 5 and planner.divisor_exact(rect, uneven) is None
    usable, d = planner.uniform_outer(rect, uneven)
    assert usable < uneven and planner.divisor_exact(rect, usable) == d


def test_inclusion_exclusion_forms():
    import random

    rnd = random.Random(1)
    for k in (1, 2, 3, 4, 5):
        sets = [set(rnd.sample(range(9), rnd.randrange(9))) for _ in range(k)]
        true = sum(len(set(t)) == k for t in _tuples(sets))
        assert iep.count_python(sets) == true
        if k < 5:
            assert iep.count_python(sets, "pairs") == true
    assert [len(iep.terms(k, "pairs")) for k in (2, 3, 4)] == [2, 8, 64] and [len(iep.terms(k)) for k in (2, 3, 4, 5)] == [2, 5, 15, 52]
    sets = [set(range(i, i + 5)) for i in range(6)]
    assert [len(c) for c in iep.components(6, [(0, 1), (1, 2), (3, 4)])] == [3, 2, 1]
    assert iep.term_cardinality(6, [(0, 1), (1, 2), (3, 4)], sets) == 3 * 4 * 5


def _tuples(sets):
    from itertools import product

    return product(*sets)


def test_every_order_is_counted_once():
    for name in CATALOGUE:
        p = named(name)
        if p.n <= 5:
            for s in symmetry.restriction_sets(p)[:20]:
                assert set(symmetry.overcount(p, s)) == {1}
    assert len(list(permutations(range(4)))) == len(schedules.all_orders(named("k4")))


def test_preparation_is_timed():
    done = planner.prepare(named("w2"), STATS)
    assert set(done.timings) == {"automorphisms", "restriction_sets", "schedules", "ranking", "generation"} and done.ranked > 0
