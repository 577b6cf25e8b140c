"""Other ways to match and count: what the planned engine is compared with. All return pattern and n, like api.count."""

from __future__ import annotations

import random
from itertools import combinations, permutations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import api
from ..plans import planner, schedules, symmetry
from ..plans.cost_model import GraphStats
from ..plans.patterns import Pattern
from ..plans.planner import Configuration
from ..sources.graphs import Graph, first_row, in_classes, may_replicate

#: Of one direction of an edge in a join's table.
EDGE_BYTES = 40


def _named(df: DataFrame, p: Pattern, name: str | None) -> DataFrame:
    return df.select(F.lit(name or p.text()).alias("pattern"), F.col("n").cast("long").alias("n"))


def symmetric(g: Graph, a: str, b: str) -> DataFrame:
    """Both directions of every edge."""
    e = g.edges.select(F.col("src").alias(a), F.col("dst").alias(b))
    return e if g.directed else e.unionByName(e.select(F.col(b).alias(a), F.col(a).alias(b)))


def edge_join(g: Graph, p: Pattern, restrictions=frozenset(), order=None, checkpoint: bool = False, each=None, seeds=None, deal: int = 0) -> DataFrame:
    """Bindings by joining one edge relation per pattern edge; all intermediate tuples are full rows.

    checkpoint: write every intermediate relation, as an engine on persistent storage does. each: a condition on the
    rows of each step, made from the bound vertices. seeds: condition on ``id``, the first vertex. deal: the edges go to every task
    whole, and the first vertex's rows to that many partitions, so that no tuple is shuffled.
    """
    whole = F.broadcast if deal else lambda e: e
    order = order or planner.choose(p, GraphStats(10_000, 60_000, 30_000)).order
    rules, df, bound, written = symmetry.closure(restrictions), None, [], None
    for v in order:
        name = p.names[v]
        earlier = [u for u in bound if p.adjacent(u, v)]
        if df is None:
            df = symmetric(g, "id", "_").select("id").where(seeds if seeds is not None else F.lit(True)).distinct().select(F.col("id").alias(name))
            df = df.repartition(deal, name) if deal else df
        for k, u in enumerate(earlier):
            # an edge relation from u to v, or from v to u where only that direction is in a directed pattern
            ways = [(u, v)] if not p.directed else [e for e in ((u, v), (v, u)) if e in p.edges]
            for j, (a, b) in enumerate(ways):
                e = whole(symmetric(g, p.names[a], p.names[b]))
                df = df.join(e, p.names[u]) if k + j == 0 else df.join(e, [p.names[u], name], "left_semi")
        ok = F.lit(True)
        for u in bound:
            if (u, v) in rules:
                ok &= F.col(p.names[u]) > F.col(name)
            elif (v, u) in rules:
                ok &= F.col(name) > F.col(p.names[u])
            elif not p.adjacent(u, v):
                ok &= F.col(p.names[u]) != F.col(name)
        df = df.where(ok)
        bound.append(v)
        if each is not None and len(bound) > 1:
            df = df.where(each(bound))
        if checkpoint and len(bound) > 1:
            df, before = _written(df), written
            if before is not None:
                _forget(before)
            written = df
    return df


def _written(df: DataFrame) -> DataFrame:
    """Write the rows to the checkpoint folder; the shuffle files of their query are given back at once."""
    conf, key = df.sparkSession.conf, "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = conf.get(key, "false")
    conf.set(key, "true")
    try:
        return df.select("*").checkpoint()
    finally:
        conf.set(key, before)


def _forget(df: DataFrame) -> None:
    """Take the files of a written relation that nothing reads any more out of the checkpoint folder."""
    file = df._jdf.queryExecution().logical().rdd().getCheckpointFile()
    if file.isDefined():
        path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(file.get())
        path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


def tuple_bytes(g: Graph, p: Pattern, order) -> float:
    """An estimate of the bytes of all tuples that edge joins in this order pass on: mean neighbours of an edge's end for a
    new vertex, the share of closed wedges for each further edge, and one of the copies of each subgraph."""
    ends, squares = g.moments()
    rows, sent = float(g.stats().n_vertices), 0.0
    closed = min(1.0, 6 * g.stats().n_triangles / max(1, squares - ends))
    for i, v in enumerate(order[1:], 1):
        rows *= squares / max(1, ends)
        sent += rows * 8 * (i + 1)
        rows *= closed ** (sum(p.adjacent(u, v) for u in order[:i]) - 1)
    return sent / len(symmetry.automorphisms(p))


def _joined(g: Graph, p: Pattern, restrictions=frozenset()) -> DataFrame:
    """One row, n: the bindings of edge joins, in one job that shuffles no tuple where the edges are few, else by classes of the first
    vertex where the tuples of all would be too many at once."""
    ends, squares = g.moments()
    if may_replicate(EDGE_BYTES * ends):
        return edge_join(g, p, restrictions, deal=api.DEALT * g.spark.sparkContext.defaultParallelism).agg(F.count(F.lit(1)).alias("n"))
    rows, sent = float(g.stats().n_vertices), 0.0
    for i in range(1, p.n):
        rows *= squares / max(1, ends)
        sent += rows * 8 * (i + 1)
    return in_classes(g, sent, lambda own: edge_join(g, p, restrictions, seeds=own).agg(F.count(F.lit(1)).alias("n")), "n long")


def naive(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """All mappings by edge joins, divided by the number of automorphisms."""
    d = len(symmetry.automorphisms(p))
    return _named(_joined(g, p).select(F.expr(f"n div {d}").alias("n")), p, name)


def single_set(g: Graph, p: Pattern, name: str | None = None, method: str = "enumerate") -> DataFrame:
    """One restriction set per pattern, made without regard to its effect, and an order chosen for it."""
    c = planner.choose(p, g.stats(), restrictions=symmetry.orbit_restrictions(p))
    return api.count(g, p, c, method=method, name=name)


def loop_compiler(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """Nested loops in the best order under a random-graph estimate, without inequalities."""
    s = g.stats()
    flat = GraphStats(s.n_vertices, s.n_edges, int((2 * s.n_edges) ** 3 / max(1, s.n_vertices) ** 3 / 6))
    c = planner.choose(p, flat, restrictions=frozenset())
    d = len(symmetry.automorphisms(p))
    return _named(api.count(g, p, c, method="enumerate", distinct=False).select(F.expr(f"n div {d}").alias("n")), p, name)


def extension(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """Vertex-by-vertex extension of partial matches; a copy is dropped when a smaller image of it exists.

    The check is made at each step, on the partial match: of the automorphisms that move bound vertices only, none may
    map it to a smaller one. A match that is least among all its images is least among those, which differ from it in
    the bound vertices alone, so no whole match that is kept loses a part on the way.
    """
    order = schedules.efficient(p, 1)[0][0]
    group = symmetry.automorphisms(p)

    def canonical(bound: list[int]) -> F.Column:
        own = [a for a in group if all(a[v] == v for v in range(p.n) if v not in bound)]
        listed = sorted(bound)
        mine = F.array(*(F.col(p.names[v]) for v in listed))
        return mine == F.array_min(F.array(*(F.array(*(F.col(p.names[a[v]]) for v in listed)) for a in own)))

    return _named(edge_join(g, p, order=order, each=canonical).agg(F.count(F.lit(1)).alias("n")), p, name)


def filter_process(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """Expand all connected vertex sets of the pattern's size, then look in each for the pattern."""
    s = symmetric(g, "u", "v")
    sets = s.select(F.array_sort(F.array("u", "v")).alias("set")).distinct()
    for _ in range(p.n - 2):
        grown = sets.select("set", F.explode("set").alias("u")).join(s, "u").where(~F.array_contains("set", F.col("v")))
        sets = grown.select(F.array_sort(F.array_append("set", F.col("v"))).alias("set")).distinct()
    pairs = list(combinations(range(p.n), 2))
    rows = sets.select("set", *(F.col("set")[i].alias(f"x{i}") for i in range(p.n)))
    edges = g.edges
    inside = rows.select("set", F.explode(F.array(*(F.struct(F.col(f"x{i}").alias("src"), F.col(f"x{j}").alias("dst"), F.lit(k).alias("k")) for k, (i, j) in enumerate(pairs)))).alias("e"))
    inside = inside.select("set", "e.src", "e.dst", "e.k").join(edges, ["src", "dst"]).groupBy("set").agg(F.sum(F.expr("shiftleft(1, k)")).cast("int").alias("mask"))
    places = {sum(1 << pairs.index(tuple(sorted((q[a], q[b])))) for a, b in p.edges) for q in permutations(range(p.n))}
    hits = sum((F.when(F.col("mask").bitwiseAND(F.lit(m)) == m, 1).otherwise(0) for m in sorted(places)), F.lit(0))
    return _named(inside.agg(F.coalesce(F.sum(hits), F.lit(0)).alias("n")), p, name)


def relational_tuples(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """Edge joins whose intermediate relations are all written; one copy kept by the orbit set.

    Where they would be too large at once they are written by classes of the first vertex. A relation's files go when the next one stands.
    """
    order = planner.choose(p, GraphStats(10_000, 60_000, 30_000)).order

    def run(own):
        df = edge_join(g, p, symmetry.orbit_restrictions(p), order=order, checkpoint=True, seeds=own)
        n = first_row(df.agg(F.count(F.lit(1)).alias("n")))[0]
        _forget(df)
        return g.spark.createDataFrame([(n,)], "n long")

    return _named(in_classes(g, tuple_bytes(g, p, order), run, "n long", tuples=True), p, name)


def motif_dataframe(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """Edge joins of one query, one copy kept by the orbit set."""
    return _named(_joined(g, p, symmetry.orbit_restrictions(p)), p, name)


def twins(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """Inequalities between vertices with equal neighbours only; what they leave is divided out where it is uniform."""
    r = symmetry.twin_restrictions(p)
    usable, d = planner.uniform_outer(p, r)
    c = planner.choose(p, g.stats(), restrictions=usable)
    return _named(api.count(g, p, c, method="enumerate").select(F.expr(f"n div {d}").alias("n")), p, name)


def sample_count(g: Graph, p: Pattern, trials: int = 2000, seed: int = 5, name: str | None = None) -> DataFrame:
    """Estimate: count with the first vertex in a hash sample of about ``trials`` vertices, scaled up; with the exact
    share that was drawn. Weak where matches are few."""
    n = g.stats().n_vertices
    share = min(1.0, trials / n) if n else 1.0
    c = planner.choose(p, g.stats(), restrictions=frozenset())
    keep = F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 20)) < int(share * (1 << 20))
    drawn = g.adjacency().agg(F.avg(keep.cast("double")).alias("share"))
    rows = api.match(g, p, c, distinct=False, seeds=keep).agg(F.count(F.lit(1)).alias("hits")).crossJoin(drawn)
    d = len(symmetry.automorphisms(p))
    return rows.select(F.lit(name or p.text()).alias("pattern"), (F.col("hits") / F.col("share") / d).alias("estimate"), "hits", "share")


def local_loops(edges: list[tuple[int, int]], p: Pattern) -> int:
    """One thread, plain Python: the test oracle."""
    around: dict[int, set[int]] = {}
    back: dict[int, set[int]] = {}
    for a, b in edges:
        around.setdefault(a, set()).add(b)
        (back if p.directed else around).setdefault(b, set()).add(a)
    rules = symmetry.orbit_restrictions(p)
    order = schedules.efficient(p, 1)[0][0]
    vertices = set(around) | set(back)

    def extend(row: dict[int, int], i: int) -> int:
        if i == p.n:
            return 1
        v, sets = order[i], []
        for u in order[:i]:
            if not p.directed and p.adjacent(u, v):
                sets.append(around.get(row[u], set()))
            if p.directed and (u, v) in p.edges:
                sets.append(around.get(row[u], set()))
            if p.directed and (v, u) in p.edges:
                sets.append(back.get(row[u], set()))
        total = 0
        for x in set.intersection(*sets) if sets else vertices:
            row[v] = x
            if x not in (row[u] for u in order[:i]) and all(row[a] > row[b] for a, b in rules if a in row and b in row and v in (a, b)):
                total += extend(row, i + 1)
            del row[v]
        return total

    return extend({}, 0)


def star_join(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """Joins of star units: a vertex with all its not yet covered neighbours at a time."""
    s = symmetric(g, "c", "x")
    left, units = set(p.edges), []
    while left:
        center = max(range(p.n), key=lambda v: sum(v in e for e in left))
        leaves = sorted({a if b == center else b for a, b in left if center in (a, b)})
        units.append((center, leaves))
        left -= {e for e in left if center in e}
    units.sort(key=lambda u: -len(u[1]))
    df, have = None, set()
    while units:
        k = next((i for i, (c, ls) in enumerate(units) if not have or ({c, *ls} & have)), 0)
        center, leaves = units.pop(k)
        star = None
        for leaf in leaves:
            one = s.select(F.col("c").alias(p.names[center]), F.col("x").alias(p.names[leaf]))
            star = one if star is None else star.join(one, p.names[center])
        names = {center, *leaves}
        df = star if df is None else df.join(star, [p.names[v] for v in sorted(names & have)])
        have |= names
        df = _apart(df, p, have)
    return _named(df.agg(F.count(F.lit(1)).alias("n")), p, name)


def clique_join(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """Joins of clique units: triangles first, then edges for what they leave."""
    left, units = set(p.edges), []
    for t in combinations(range(p.n), 3):
        own = set(combinations(t, 2))
        if own <= set(p.edges) and own & left:
            units.append(t)
            left -= own
    units += sorted(left)
    triangle = api.match(g, Pattern.parse("A-B, A-C, B-C"), distinct=False)
    df, have = None, set()
    while units:
        k = next((i for i, u in enumerate(units) if set(u) & have), 0)
        u = units.pop(k)
        names = [p.names[v] for v in u]
        unit = triangle.select(*(F.col(c).alias(x) for c, x in zip("ABC", names, strict=True))) if len(u) == 3 else symmetric(g, *names)
        df = unit if df is None else df.join(unit, [p.names[v] for v in u if v in have])
        have |= set(u)
        df = _apart(df, p, have)
    return _named(df.agg(F.count(F.lit(1)).alias("n")), p, name)


def _apart(df: DataFrame, p: Pattern, have: set[int]) -> DataFrame:
    """Different ids, and the orbit set's inequalities, among the vertices bound so far."""
    rules = symmetry.closure(symmetry.orbit_restrictions(p))
    for a, b in combinations(sorted(have), 2):
        x, y = F.col(p.names[a]), F.col(p.names[b])
        df = df.where(x > y if (a, b) in rules else y > x if (b, a) in rules else x != y)
    return df


def clique_dag(g: Graph, k: int, name: str | None = None) -> DataFrame:
    """k-cliques on the degree-oriented graph: successors intersected level by level, no inequality needed."""
    from ..sources.graphs import oriented

    succ = oriented(g).groupBy("a").agg(F.sort_array(F.collect_list("b")).alias("s"))
    df = succ.select(F.explode("s").alias("v"), F.col("s").alias("c"))
    for level in range(k - 2):
        df = df.join(succ.select(F.col("a").alias("v"), "s"), "v").select(F.array_intersect("c", "s").alias("c"))
        if level < k - 3:
            df = df.select(F.explode("c").alias("v"), "c")
    total = df.agg(F.coalesce(F.sum(F.size("c")), F.lit(0)).alias("n")) if k > 2 else df.agg(F.count(F.lit(1)).alias("n"))
    return total.select(F.lit(name or f"{k}-clique").alias("pattern"), F.col("n").cast("long").alias("n"))


def unfiltered(g: Graph, p: Pattern, phases: int, name: str | None = None) -> DataFrame:
    """The same model and restriction sets over orders that pass fewer phases."""
    return api.count(g, p, planner.choose(p, g.stats(), phases=phases), method="enumerate", name=name)


def no_iep(g: Graph, p: Pattern, name: str | None = None) -> DataFrame:
    """The configuration chosen for inclusion-exclusion, enumerated."""
    c = planner.choose_iep(p, g.stats())
    return api.count(g, p, Configuration(p, c.order, c.restrictions), method="enumerate", name=name)


BASELINES = {
    "naive": naive, "single_set": single_set, "loop_compiler": loop_compiler, "extension": extension, "filter_process": filter_process,
    "relational_tuples": relational_tuples, "motif_dataframe": motif_dataframe, "twins": twins, "star_join": star_join, "clique_join": clique_join, "no_iep": no_iep,
}


def random_graph(n: int, m: int, seed: int = 0) -> list[tuple[int, int]]:
    """A fixture for tests: m distinct edges on n vertices."""
    rng = random.Random(seed)
    every = list(combinations(range(n), 2))
    return sorted(rng.sample(every, min(m, len(every))))


def monte_carlo_interval(hits: float, share: float, divisor: int) -> tuple[float, float]:
    """A rough 95% interval of a sampled count."""
    half = 1.96 * np.sqrt(max(hits, 1.0))
    return max(0.0, hits - half) / share / divisor, (hits + half) / share / divisor
