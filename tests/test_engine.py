"""The engine on small graphs: every configuration, method and executor against plain Python loops."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from weftgraph import api, metrics
from weftgraph.operators import baselines, dense, executor, graph_ops, iep
from weftgraph.plans import compiler, planner, schedules, symmetry
from weftgraph.plans.patterns import Pattern, clique, connected_shapes, named
from weftgraph.plans.planner import Configuration
from weftgraph.sources import graphs

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def random_graph(spark):
    edges = baselines.random_graph(14, 40, 3)
    return graphs.from_edges(spark.createDataFrame(edges, "src long, dst long"), name="random"), edges


@pytest.fixture(scope="module")
def d1(spark):
    return graphs.graph(spark, SMALL, "d1")


def test_entry(spark):
    assert entry.entry(spark).first()["n"] == 36_212


@pytest.mark.parametrize("name,n", [("wedge", 16_259), ("triangle", 830), ("rectangle", 4_327), ("tailed", 33_956), ("diamond", 2_557), ("k4", 180), ("w2", 6_342), ("w3", 20_268), ("w4", 36_589), ("w6", 620), ("prism", 1_167)])
def test_known_counts(d1, name, n):
    assert api.count(d1, named(name), method="iep").first()["n"] == n
    assert api.count(d1, named(name), method="enumerate").first()["n"] == n


@pytest.mark.parametrize("name", ["triangle", "rectangle", "diamond", "star3", "path4", "k4", "c5", "w1", "w2", "w4"])
def test_methods_agree_with_loops(random_graph, name):
    g, edges = random_graph
    p = named(name)
    true = baselines.local_loops(edges, p)
    assert api.count(g, p, method="enumerate").first()["n"] == true
    assert api.count(g, p, method="iep").first()["n"] == true
    assert api.count(g, p, method="iep", form="pairs").first()["n"] == true if p.n < 6 else True
    assert api.match(g, p).count() == true and api.match(g, p).select(api.edge_key(p)).distinct().count() == true
    assert api.count(g, p, method="enumerate", distinct=False).first()["n"] == true * len(symmetry.automorphisms(p))
    assert executor.replicated_count(g, p).first()["n"] == true


def test_every_configuration_of_the_house(random_graph):
    g, edges = random_graph
    p = named("w1")
    true = baselines.local_loops(edges, p)
    for o in schedules.efficient(p)[0][::3]:
        for s in symmetry.restriction_sets(p):
            c = Configuration(p, o, s)
            assert api.count(g, p, c, method="enumerate").first()["n"] == true
            assert api.iep_count(g, planner.with_iep(c)).first()["n"] == true


@pytest.mark.parametrize("b", sorted(baselines.BASELINES))
def test_baselines(random_graph, b):
    g, edges = random_graph
    for name in ("triangle", "rectangle", "w1"):
        assert baselines.BASELINES[b](g, named(name)).first()["n"] == baselines.local_loops(edges, named(name)), name


def test_induced_identities(random_graph):
    g, _ = random_graph
    plain = {r["pattern"]: r["n"] for r in api.motifs(g, 4).collect()}
    induced = {r["pattern"]: r["n"] for r in api.motifs(g, 4, induced=True).collect()}
    by = {len(p.edges) * 10 + max(len(a) for a in p.around): p.text() for p in connected_shapes(4)}
    k4, diamond, rectangle = by[63], by[53], by[42]
    assert induced[k4] == plain[k4] and induced[diamond] == plain[diamond] - 6 * plain[k4]
    assert induced[rectangle] == plain[rectangle] - induced[diamond] - 3 * plain[k4]


def test_induced_under_every_order(random_graph):
    """Also where the last vertex is adjacent to all others, so that only earlier loops see a missing edge."""
    g, _ = random_graph
    p = named("diamond")
    true = api.match(g, p, induced=True).count()
    for o in schedules.efficient(p, 1)[0]:
        c = Configuration(p, o, symmetry.orbit_restrictions(p))
        assert api.count(g, p, c, method="enumerate", induced=True).first()["n"] == true
        free = Configuration(p, o, frozenset())
        assert api.count(g, p, free, method="enumerate", induced=True, distinct=False).first()["n"] == true * len(symmetry.automorphisms(p))


def test_complete_graph_closed_form(spark):
    g = graphs.graph(spark, SMALL, "d4")
    assert api.count(g, named("w1")).first()["n"] == 15_120 and api.cliques(g, 5).first()["n"] == 252
    assert baselines.clique_dag(g, 4).first()["n"] == 210


def test_edge_cases(spark):
    empty = graphs.graph(spark, SMALL, "d6")
    assert empty.stats().n_edges == 0 and api.count(empty, named("triangle")).first()["n"] == 0 and api.match(empty, named("w1")).count() == 0
    rows = [(1, 2), (2, 1), (1, 1), (None, 3), (2, 3), (2**40, 1), (3, 1)]
    g = graphs.from_edges(spark.createDataFrame(rows, "src long, dst long"))
    assert g.edges.count() == 4 and api.count(g, named("triangle")).first()["n"] == 1
    assert api.count(g, clique(5)).first()["n"] == 0 and not api.exists(g, named("k4")) and api.exists(g, named("triangle"))
    bipartite = graphs.graph(spark, SMALL, "d5")
    assert api.count(bipartite, named("triangle")).first()["n"] == 0
    named_graph, keys = graphs.from_keys(spark.createDataFrame([("x", "y"), ("y", "z"), ("x", "z")], "a string, b string"), "a", "b")
    assert api.count(named_graph, named("triangle")).first()["n"] == 1 and sorted(r["id"] for r in keys.collect()) == [0, 1, 2]


def test_relabelling_changes_nothing(random_graph, spark):
    _, edges = random_graph
    moved = graphs.from_edges(spark.createDataFrame([((a * 7 + 3) % 101, (b * 7 + 3) % 101) for a, b in edges], "src long, dst long"))
    assert api.count(moved, named("w1")).first()["n"] == baselines.local_loops(edges, named("w1"))


def test_directed_and_labelled(spark):
    rows = [(1, 2), (2, 3), (3, 1), (3, 4), (2, 4)]
    g = graphs.from_edges(spark.createDataFrame(rows, "src long, dst long"), directed=True)
    for text in ("A>B, B>C", "A>B, B>C, C>A", "A>B, A>C", "A>B, A>C, B>C"):
        p = Pattern.parse(text)
        assert api.count(g, p, method="enumerate").first()["n"] == baselines.local_loops(rows, p), text
    labels = spark.createDataFrame([(1, "a"), (2, "b"), (3, "a"), (4, "b")], "id long, label string")
    u = graphs.from_edges(spark.createDataFrame(rows, "src long, dst long"), labels=labels)
    assert api.count(u, Pattern.parse("A-B, A-C, B-C", vlabels={"A": "a", "B": "a", "C": "b"})).first()["n"] == 1
    marked = spark.createDataFrame([(a, b, "red" if a == 2 else "blue") for a, b in rows], "src long, dst long, elabel string")
    e = graphs.from_edges(marked, directed=True)
    assert api.count(e, Pattern.parse("A>B, B>C", elabels={"A>B": "blue", "B>C": "red"}), method="enumerate").first()["n"] == 2


def test_chunked_and_oriented(d1, spark):
    assert executor.chunked_triangles(d1, 4).first()["n_triangles"] == 830 == graphs.triangle_count(d1).first()["n_triangles"]
    assert executor.chunked(d1, 4).select(F.max(F.size("nbrs"))).first()[0] < 16
    with pytest.raises(ValueError):
        executor.to_csr(d1, limit=10)
    assert graph_ops.k_core(d1, 3).count() <= d1.edges.count()


@pytest.fixture(scope="module")
def hubs(spark):
    """A power law: two vertices adjacent to nearly all, a few to many, the rest to few."""
    rng = random.Random(4)
    edges = {(0, v) for v in range(1, 900)} | {(1, v) for v in range(2, 700, 2)}
    for v in range(2, 900):
        edges |= {tuple(sorted((v, w))) for w in rng.sample(range(2, 900), max(1, 120 // v)) if w != v}
    return graphs.from_edges(spark.createDataFrame(sorted(edges), "src long, dst long"), name="hubs"), sorted(edges)


@pytest.mark.parametrize("name", ["wedge", "triangle", "rectangle", "diamond", "k4", "w1"])
def test_spread_on_hubs(hubs, name, monkeypatch):
    g, edges = hubs
    p = named(name)
    true = api.count(g, p, method="enumerate", executor="lists").first()["n"]
    assert executor.spread_count(g, p, size=32).first()["n"] == true
    if name in ("triangle", "k4"):
        assert true == baselines.local_loops(edges, p)
    monkeypatch.setattr(executor, "HUB_DEGREE", 100)
    assert api.count(g, p).first()["n"] == true and api.match(g, p).count() == true


def test_spread_keys_are_even(hubs):
    """No row is long, and no key gathers a hub's prefixes."""
    g, _ = hubs
    chunks = g.chunks(32)
    assert chunks.select(F.max(F.size("nbrs"))).first()[0] <= 64 and g.max_degree() == 899
    per_key = chunks.where("id = 0").groupBy("chunk").count().select(F.min("count"), F.max("count")).first()
    assert per_key[0] == per_key[1] == 6  # 29 chunks
    met = executor.spread(g, planner.choose(named("wedge"), g.stats()), 32, loops=2).count()
    assert met <= 2 * g.edges.count()


def test_spread_on_a_bipartite_graph(spark):
    d5 = graphs.graph(spark, SMALL, "d5")
    for name in ("wedge", "rectangle", "diamond", "w1"):
        assert executor.spread_count(d5, named(name), size=8).first()["n"] == api.count(d5, named(name), method="enumerate").first()["n"]


def test_replicated_in_parts(random_graph, monkeypatch):
    g, edges = random_graph
    monkeypatch.setattr(executor, "PAIRS_AT_ONCE", 5)
    csr = executor.to_csr(g)
    for name in ("triangle", "rectangle", "w1"):
        plan = compiler.loop_plan(planner.choose(named(name), g.stats()))
        first = {plan[0].vertex: np.arange(len(csr.ids))}
        assert executor.count_prefixes(csr, plan, first, 1) == baselines.local_loops(edges, named(name))


def test_k_core_by_peeling(random_graph):
    g, edges = random_graph
    left = set(edges)
    while True:
        deg = {}
        for a, b in left:
            deg[a], deg[b] = deg.get(a, 0) + 1, deg.get(b, 0) + 1
        kept = {(a, b) for a, b in left if deg[a] >= 4 and deg[b] >= 4}
        if kept == left:
            break
        left = kept
    assert {tuple(r) for r in graph_ops.k_core(g, 4).collect()} == left


def test_plans(d1, spark):
    """What the optimiser must keep: intersections evaluated once, filters in the scan, nothing in Python."""
    p = named("w1")
    c = planner.choose(p, d1.stats())
    text = api.match(d1, p, c)._jdf.queryExecution().executedPlan().toString()
    assert text.count("array_intersect(") == sum(len(loop.temps) for loop in compiler.loop_plan(c)) and "Python" not in text and "CartesianProduct" not in text
    iep_text = api.iep_count(d1, planner.with_iep(c))._jdf.queryExecution().executedPlan().toString()
    assert "transform(" not in iep_text and "Python" not in iep_text
    scan = graphs.BUILDERS["d1"](spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(l_returnflag,R)" in scan and "l_extendedprice" not in scan


@pytest.mark.parametrize("name,taken,looked", [("tailed", 1, 0), ("diamond", 1, 0), ("star3", 0, 0), ("wedge", 0, 0), ("rectangle", 1, 0), ("path4", 1, 0), ("w2", None, 0)])
def test_suffix_plans(d1, name, taken, looked):
    """No intersection where one list's candidates hold the other's, no probe whose answer the pattern gives, lengths instead of lists."""
    c = planner.choose_iep(named(name), d1.stats())
    found = iep.blocks(c, c.iep_k)
    assert sum(len(b.probed) for b in found.values()) == looked
    text = api.iep_count(d1, c)._jdf.queryExecution().executedPlan().toString()
    distinct = {b.operands: b for b in found.values()}
    made = {a for b in distinct.values() for a in b.arrays if len(a) > 1} | {b.operands for b in distinct.values() if len(b.arrays) > 1}
    assert text.count("array_intersect(") == (len(made) if taken is None else taken)
    assert text.count("array_contains(") == looked


def test_measures(random_graph):
    g, _ = random_graph
    p = named("w1")
    meter = metrics.LoopWork(g)
    found = metrics.configurations(g, p)
    works = [meter.of(c) for c in found]
    assert metrics.regret(g, p) == works[0] / min(works) - 1 >= 0
    low, high, ratio = metrics.spread(g, p)
    assert (low, high) == (min(works), max(works)) and ratio >= 1
    assert meter.of(metrics.oracle(g, p)) == low
    assert metrics.rank_corr([1, 2, 3], [2, 4, 9]) == pytest.approx(1) and metrics.qerror(2, 8) == 4
    assert metrics.agree(g, p, {"a": lambda: api.count(g, p), "b": lambda: baselines.single_set(g, p)})
    rows = metrics.loop_rows(g, found[0])
    assert rows[-1][1] == api.count(g, p).first()["n"] and rows[0][1] == g.stats().n_vertices
    assert metrics.timed(g, lambda: api.count(g, p), 60).status == "ok"


def test_sampling(d1):
    r = baselines.sample_count(d1, named("triangle"), trials=10**6).first()
    assert r["estimate"] == pytest.approx(830) and r["share"] == 1.0


def test_triangles_in_classes(spark):
    """The same triangles in one job and in hash classes of vertices, whose lists are never in flight at once."""
    from itertools import combinations

    from weftgraph.sources.graphs import from_edges, triangle_count

    rows = [(a, b) for a, b in combinations(range(12), 2)] + [(a, 100 + a) for a in range(12)] + [(3, 100), (200, 201)]
    g = from_edges(spark.createDataFrame(rows, "src long, dst long"))
    one = triangle_count(g).first()[0]
    sizes = [len(s) for (s,) in g._tables["successors"].select("s").collect()]
    many = triangle_count(g, in_flight=200)
    assert sum(n * (n - 1) * 4 for n in sizes) > 400 and "LogicalRDD" in many._jdf.queryExecution().analyzed().toString()
    assert one == many.first()[0] == 220 + 1


def test_counts_in_classes(spark, monkeypatch):
    """Counts over a bound on what is in flight run as several jobs, one after another, with the same sums."""
    from itertools import combinations

    from weftgraph import api
    from weftgraph.operators import baselines, executor
    from weftgraph.plans.patterns import named
    from weftgraph.sources import graphs

    g = graphs.from_edges(spark.createDataFrame([(a, b) for a, b in combinations(range(9), 2)] + [(0, 20), (20, 21)], "src long, dst long"))
    house = named("w1")
    runs = {
        "enumerate": lambda: api.count(g, house, method="enumerate"), "iep": lambda: api.count(g, house, method="iep"), "k4": lambda: api.cliques(g, 4),
        "spread": lambda: executor.spread_count(g, named("diamond"), size=4), "naive": lambda: baselines.naive(g, named("rectangle")), "motif": lambda: baselines.motif_dataframe(g, named("rectangle")),
    }
    whole = {k: f().first()["n"] for k, f in runs.items()}
    jobs, kept = [], graphs.first_row
    monkeypatch.setattr(graphs, "first_row", lambda df: jobs.append(1) or kept(df))
    for k, f in runs.items():
        monkeypatch.setattr(graphs, "IN_FLIGHT", 2500)
        jobs.clear()
        assert f().first()["n"] == whole[k] and len(jobs) > 1, k


def test_edge_joins_by_classes_leave_no_files(spark, monkeypatch):
    """Where tuples would be too many at once they are made by classes; written relations go when they are read."""
    from pathlib import Path

    from weftgraph.queries import relational

    assert graphs.TUPLES_IN_FLIGHT > graphs.IN_FLIGHT
    g, p, ran, own = graphs.graph(spark, SMALL, "d1"), named("w1"), [], graphs.first_row
    monkeypatch.setattr(graphs, "first_row", lambda df: ran.append(1) or own(df))
    monkeypatch.setattr(graphs, "TUPLES_IN_FLIGHT", int(baselines.tuple_bytes(g, p, range(p.n)) / 3))
    true = api.count(g, p).first()["n"]
    ran.clear()
    assert relational.QUERIES["op_house_sql_text"](spark, SMALL).first()["n"] == true > 0 and len(ran) >= 3
    spark.range(1).checkpoint()
    folder = Path(spark.sparkContext.getCheckpointDir().removeprefix("file:"))
    before = {x for x in folder.iterdir()}
    assert baselines.relational_tuples(g, p).first()["n"] == true and {x for x in folder.iterdir()} <= before and len(ran) >= 6


def test_small_lists_go_to_every_task(d1, monkeypatch):
    """Where rows would be many but the lists are few, a count is one job that shuffles no row to them."""
    p = named("w5")
    plan = compiler.loop_plan(planner.choose(p, d1.stats()))
    true = api.count(d1, p, method="enumerate", executor="lists", hint="shuffle_hash").first()["n"]
    bound = 4 * (8 * d1.moments()[0] + 64 * d1.stats().n_vertices)
    assert compiler.in_flight(d1, plan) > 4 * bound
    jobs, kept = [], graphs.first_row
    monkeypatch.setattr(graphs, "first_row", lambda df: jobs.append(1) or kept(df))
    monkeypatch.setattr(graphs, "IN_FLIGHT", bound)
    found = api.count(d1, p, method="enumerate")
    assert found.first()["n"] == true > 0 and not jobs
    plan_text = found._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan_text and "SortMergeJoin" not in plan_text and "ShuffledHashJoin" not in plan_text


def test_rows_that_can_not_match_end_early(d1):
    """Vertices that lie in an intersection together need as many members, bound ones included; the counts stay."""
    p = named("prism")
    c = planner.choose_iep(p, d1.stats())
    arrays, sizes = iep.kept(c, c.iep_k)
    plan = compiler.loop_plan(c, p.n - c.iep_k, c.outer, False, arrays, sizes)
    b, d = p.names.index("B"), p.names.index("D")
    assert compiler.members(p, ((b, "n", None), (d, "n", None))) == 2  # A and E
    rows = [compiler.emit(d1, c, plan, prune=x).count() for x in (False, True)]
    assert 0 < rows[1] < rows[0], rows
    assert api.iep_count(d1, c).first()["n"] == 1_167


def test_cliques_by_blocks(spark, random_graph, monkeypatch):
    """Dense graphs: products of blocks, by whatever ranges; no list is gathered."""
    g, edges = random_graph
    for k in (3, 4):
        assert dense.block_cliques(g, k, block=4).first()["n"] == baselines.local_loops(edges, clique(k))
    monkeypatch.setattr(dense, "LEAST_SQUARES", 1)
    whole = graphs.from_edges(spark.range(12).selectExpr("explode(sequence(0L, 11L)) as src", "id * 1000 as dst").selectExpr("src * 1000 as src", "dst"))
    found = api.cliques(whole, 4, name="k4")
    assert tuple(found.first()) == ("k4", 495) and "array_intersect" not in found._jdf.queryExecution().executedPlan().toString()
    assert api.cliques(whole, 5).first()["n"] == 792


def test_triangles_by_blocks(spark, monkeypatch):
    """The statistics of a dense graph without a list; a sparse one with a hub keeps its lists."""
    monkeypatch.setattr(dense, "LEAST_SQUARES", 1)
    rng = random.Random(6)
    edges = [(a, b) for a in range(40) for b in range(a + 1, 40) if rng.random() < 0.7]
    g = graphs.from_edges(spark.createDataFrame(edges, "src long, dst long"))
    assert tuple(g.stats_frame().first()) == (40, len(edges), baselines.local_loops(edges, clique(3))) and "successors" not in g._tables
    star = graphs.from_edges(spark.createDataFrame([(i, i + 1) for i in range(0, 900, 2)] + [(-1, i) for i in range(30)], "src long, dst long"))
    assert star.stats().n_triangles == 15 and "successors" in star._tables
    empty = graphs.from_edges(spark.createDataFrame([], "src long, dst long"))
    assert dense.block_cliques(empty, 3).first()["n"] == 0


@pytest.mark.parametrize("run,name", [(baselines.naive, "rectangle"), (baselines.motif_dataframe, "w1")])
def test_edge_joins_shuffle_no_tuples(d1, monkeypatch, run, name):
    """Where tuples would be many but the edges are few, edge joins are one job with the edges in every task."""
    p = named(name)
    bound = 4 * baselines.EDGE_BYTES * d1.moments()[0]
    jobs, kept = [], graphs.first_row
    monkeypatch.setattr(graphs, "first_row", lambda df: jobs.append(1) or kept(df))
    monkeypatch.setattr(graphs, "IN_FLIGHT", bound)
    found = run(d1, p)
    assert found.first()["n"] == {"rectangle": 4_327, "w1": 36_212}[name] and not jobs
    text = found._jdf.queryExecution().executedPlan().toString()
    assert text.count("BroadcastHashJoin") >= len(p.edges) and "SortMergeJoin" not in text and "ShuffledHashJoin" not in text
