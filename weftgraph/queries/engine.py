"""Queries over graphs, patterns, plans and counts."""

from __future__ import annotations

import math
from itertools import combinations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import api
from ..operators import baselines, executor
from ..plans import cost_model, planner, schedules, sql, symmetry
from ..plans.patterns import CATALOGUE, Pattern, clique, connected_shapes, named
from ..sources.graphs import BUILDERS, EDGES_SQL, edge_list, graph, shared_lines, triangle_count, twin_triangle_count

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def register(name: str, run, oracle: str | None = None) -> None:
    QUERIES[name] = run
    if oracle is not None:
        ORACLES[name] = oracle


def with_edges(d: str, rest: str) -> str:
    """SQL over e (edges), s (both directions) and deg (id, deg)."""
    return (
        f"WITH e AS MATERIALIZED ({EDGES_SQL[d]}), s AS MATERIALIZED (SELECT src AS a, dst AS b FROM e UNION ALL SELECT dst, src FROM e), "
        f"deg AS (SELECT a AS id, count(*) AS deg FROM s GROUP BY a) {rest}"
    )


TRIANGLES = "(SELECT count(*) FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst)"

# Graphs ---------------------------------------------------------------------------------------------------------

for _d in BUILDERS:
    register(f"edges_{_d}", lambda spark, sf, d=_d: edge_list(spark, sf, d), EDGES_SQL.get(_d))
for _d in ("d1", "d2", "d3", "d5", "d6", "d7", "d9", "d9_all"):
    register(
        f"graph_stats_{_d}", lambda spark, sf, d=_d: graph(spark, sf, d).stats_frame(),
        with_edges(_d, f"SELECT (SELECT count(*) FROM deg) AS n_vertices, (SELECT count(*) FROM e) AS n_edges, {TRIANGLES} AS n_triangles"),
    )
for _d in ("d1", "d2", "d3", "d4", "d5", "d6", "d8", "d9", "d9_all", "d11"):
    register(f"triangle_count_{_d}", lambda spark, sf, d=_d: twin_triangle_count(shared_lines(spark, sf)) if d == "d9_all" else triangle_count(graph(spark, sf, d)), with_edges(_d, f"SELECT {TRIANGLES} AS n_triangles"))


def _adjacency_d1(spark, sf):
    return graph(spark, sf, "d1").adjacency().select("id", F.posexplode("nbrs_n").alias("pos", "nbr"))


register("adjacency_d1", _adjacency_d1, with_edges("d1", "SELECT a AS id, (row_number() OVER (PARTITION BY a ORDER BY b) - 1)::INTEGER AS pos, b AS nbr FROM s"))


def _degree_stats(spark, sf):
    return graph(spark, sf, "d1").adjacency().agg(F.min("deg").alias("lo"), F.max("deg").alias("hi"), F.round(F.avg("deg"), 6).alias("mean"), F.sum(F.col("deg").cast("long") * (F.col("deg") - 1) / 2).cast("long").alias("wedges"))


register("degree_stats_d1", _degree_stats, with_edges("d1", "SELECT min(deg)::INTEGER AS lo, max(deg)::INTEGER AS hi, round(avg(deg), 6) AS mean, sum(deg * (deg - 1) // 2)::BIGINT AS wedges FROM deg"))
register(
    "degree_histogram_d1",
    lambda spark, sf: graph(spark, sf, "d1").adjacency().groupBy((F.col("deg") / 5).cast("int").alias("bucket")).agg(F.count(F.lit(1)).alias("vertices")),
    with_edges("d1", "SELECT (deg // 5)::INTEGER AS bucket, count(*) AS vertices FROM deg GROUP BY 1"),
)


def _csr_offsets(spark, sf):
    """Where each vertex's neighbours start: a prefix sum over hash ranges of ids, each range summed apart."""
    deg = graph(spark, sf, "d1").adjacency().select("id", "deg").withColumn("block", (F.col("id") / 1024).cast("long"))
    sums = deg.groupBy("block").agg(F.sum("deg").alias("n"))
    starts = sums.select("block", F.coalesce(F.sum("n").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    inside = F.coalesce(F.sum("deg").over(Window.partitionBy("block").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return deg.join(starts, "block").select("id", (F.col("start") + inside).cast("long").alias("offset"))


register("csr_offsets_d1", _csr_offsets, with_edges("d1", 'SELECT id, coalesce(sum(deg) OVER (ORDER BY id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS "offset" FROM deg'))

# Counts ---------------------------------------------------------------------------------------------------------

COUNTED = ["wedge", "triangle", "rectangle", "tailed", "diamond", "star3", "path4", "k4", "k5", "c5", "prism", "w1", "w2", "w3", "w4", "w5", "w6"]
for _n in COUNTED:
    for _d in ("d1", "d2"):
        if _d == "d2" and _n in ("c5", "prism", "k5"):
            continue
        _sql = sql.count_sql(named(_n), EDGES_SQL[_d], _n)
        # breadth over a strip of seven is the one workload whose listing order multiplies wedges on d2
        if (_n, _d) != ("w5", "d2"):
            register(f"count_{_n}_{_d}", lambda spark, sf, n=_n, d=_d: api.count(graph(spark, sf, d), named(n), method="enumerate", name=n), _sql)
            register(f"iep_{_n}_{_d}", lambda spark, sf, n=_n, d=_d: api.count(graph(spark, sf, d), named(n), method="iep", name=n), _sql)
        else:
            register(f"count_{_n}_{_d}", lambda spark, sf, n=_n, d=_d: baselines.unfiltered(graph(spark, sf, d), named(n), 1, name=n), _sql)
register("iep_pairs_form_w2_d1", lambda spark, sf: api.count(graph(spark, sf, "d1"), named("w2"), method="iep", form="pairs", name="w2"), ORACLES["count_w2_d1"])
register("count_seed_batches_w1_d1", lambda spark, sf: api.count(graph(spark, sf, "d1"), named("w1"), seed_batches=4, name="w1"), ORACLES["count_w1_d1"])
for _h in ("broadcast", "merge", "shuffle_hash"):
    register(f"count_w1_d1_{_h}", lambda spark, sf, h=_h: api.count(graph(spark, sf, "d1"), named("w1"), method="enumerate", hint=h, name="w1"), ORACLES["count_w1_d1"])
register("count_wide_w4_d1", lambda spark, sf: api.count(graph(spark, sf, "d1"), named("w4"), wide=True, name="w4").select("pattern", F.col("n").cast("long").alias("n")), ORACLES["count_w4_d1"])
for _n in ("triangle", "rectangle", "diamond", "k4", "w1", "w2", "w3"):
    register(f"match_{_n}_d1", lambda spark, sf, n=_n: api.match(graph(spark, sf, "d1"), named(n)).select(api.edge_key(named(n)).alias("edge_key")), sql.match_sql(named(_n), EDGES_SQL["d1"]))
register("match_k4_d2", lambda spark, sf: api.match(graph(spark, sf, "d2"), named("k4")).select(api.edge_key(named("k4")).alias("edge_key")), sql.match_sql(named("k4"), EDGES_SQL["d2"]))
for _n in ("triangle", "rectangle", "w1"):
    register(
        f"mappings_{_n}_d1", lambda spark, sf, n=_n: api.count(graph(spark, sf, "d1"), named(n), method="enumerate", distinct=False, name=n),
        sql.count_sql(named(_n), EDGES_SQL["d1"], _n, restrictions=frozenset()),
    )
for _n in ("wedge", "rectangle", "tailed", "diamond", "star3", "path4", "w1"):
    register(
        f"induced_{_n}_d1", lambda spark, sf, n=_n: api.count(graph(spark, sf, "d1"), named(n), method="enumerate", induced=True, name=n),
        sql.count_sql(named(_n), EDGES_SQL["d1"], _n, induced=True),
    )
for _k, _induced in ((3, False), (3, True), (4, False), (4, True)):
    register(
        f"motifs{_k}_{'induced_' if _induced else ''}d1", lambda spark, sf, k=_k, i=_induced: api.motifs(graph(spark, sf, "d1"), k, i),
        " UNION ALL ".join(f"(SELECT * FROM ({sql.count_sql(p, EDGES_SQL['d1'], p.text(), induced=_induced)}) t)" for p in connected_shapes(_k)),
    )
register("cliques4_d4", lambda spark, sf: api.cliques(graph(spark, sf, "d4"), 4, name="k4"), with_edges("d4", "SELECT 'k4' AS pattern, (v * (v - 1) * (v - 2) * (v - 3) // 24)::BIGINT AS n FROM (SELECT count(*) AS v FROM deg) x"))
register("house_closed_form_d4", lambda spark, sf: api.count(graph(spark, sf, "d4"), named("w1"), method="iep", name="w1"), with_edges("d4", "SELECT 'w1' AS pattern, (v * (v - 1) * (v - 2) * (v - 3) * (v - 4) // 2)::BIGINT AS n FROM (SELECT count(*) AS v FROM deg) x"))
register("clique_dag5_d1", lambda spark, sf: baselines.clique_dag(graph(spark, sf, "d1"), 5, name="k5"), ORACLES["count_k5_d1"])
register("triangles_bipartite_d5", lambda spark, sf: api.count(graph(spark, sf, "d5"), named("triangle"), name="triangle"), sql.count_sql(named("triangle"), EDGES_SQL["d5"], "triangle"))
register("stars_forest_d11", lambda spark, sf: api.count(graph(spark, sf, "d11"), named("star3"), name="star3"), sql.count_sql(named("star3"), EDGES_SQL["d11"], "star3"))
register("empty_graph_d6", lambda spark, sf: api.count(graph(spark, sf, "d6"), named("triangle"), name="triangle"), sql.count_sql(named("triangle"), EDGES_SQL["d6"], "triangle"))
register("cliques_doc_lines_d9", lambda spark, sf: api.cliques(graph(spark, sf, "d9"), 4, name="k4"), sql.count_sql(clique(4), EDGES_SQL["d9"], "k4"))
register("cliques_doc_lines_d9_all", lambda spark, sf: api.cliques(graph(spark, sf, "d9_all"), 4, name="k4"))
register("exists_k5_d1", lambda spark, sf: spark.createDataFrame([(api.exists(graph(spark, sf, "d1"), named("k5")),)], "found boolean"), f"SELECT n > 0 AS found FROM ({ORACLES['count_k5_d1']}) t")
_CHAIN = Pattern.parse("A>B, B>C")
register("directed_path_d12", lambda spark, sf: api.count(graph(spark, sf, "d12"), _CHAIN, name="path"), sql.count_sql(_CHAIN, EDGES_SQL["d12"], "path"))
_FAN = Pattern.parse("A>B, A>C")
register("directed_fan_d10", lambda spark, sf: api.count(graph(spark, sf, "d10"), _FAN, name="fan"), sql.count_sql(_FAN, EDGES_SQL["d10"], "fan"))


def _labelled(spark, sf):
    return api.count(graph(spark, sf, "d8"), Pattern.parse("A-B, A-C, B-C", vlabels={"A": "1", "B": "1", "C": "1"}), method="enumerate", name="triangle")


register(
    "labelled_triangle_d8", _labelled,
    with_edges("d8", "SELECT 'triangle' AS pattern, count(*) AS n FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst "
               "JOIN embeddings p ON p.vec_id = x.src AND p.label = 1 JOIN embeddings q ON q.vec_id = x.dst AND q.label = 1 JOIN embeddings r ON r.vec_id = y.dst AND r.label = 1"),
)


def _labelled_wedge(spark, sf):
    return api.count(graph(spark, sf, "d1"), Pattern.parse("A-B, A-C", vlabels={"B": "Brand#11", "C": "Brand#12"}), method="enumerate", name="wedge")


register(
    "labelled_wedge_d1", _labelled_wedge,
    with_edges("d1", "SELECT 'wedge' AS pattern, count(*) AS n FROM s x JOIN s y ON x.a = y.a AND x.b <> y.b "
               "JOIN part p ON p.p_partkey = x.b AND p.p_brand = 'Brand#11' JOIN part q ON q.p_partkey = y.b AND q.p_brand = 'Brand#12'"),
)
register("replicated_w1_d1", lambda spark, sf: executor.replicated_count(graph(spark, sf, "d1"), named("w1"), name="w1"), ORACLES["count_w1_d1"])
register("replicated_w2_d2", lambda spark, sf: executor.replicated_count(graph(spark, sf, "d2"), named("w2"), name="w2"), ORACLES["count_w2_d2"])
for _n in ("wedge", "rectangle", "diamond", "w1"):
    for _d in ("d1", "d5"):
        register(f"spread_{_n}_{_d}", lambda spark, sf, n=_n, d=_d: executor.spread_count(graph(spark, sf, d), named(n), size=32, name=n), sql.count_sql(named(_n), EDGES_SQL[_d], _n))
register("chunked_hubs_triangle_d5", lambda spark, sf: executor.chunked_triangles(graph(spark, sf, "d5"), 32), with_edges("d5", f"SELECT {TRIANGLES} AS n_triangles"))
register("chunked_hubs_triangle_d1", lambda spark, sf: executor.chunked_triangles(graph(spark, sf, "d1"), 8), with_edges("d1", f"SELECT {TRIANGLES} AS n_triangles"))
register("semi_join_triangles_d1", lambda spark, sf: baselines._named(baselines.edge_join(graph(spark, sf, "d1"), named("triangle"), symmetry.orbit_restrictions(named("triangle"))).agg(F.count(F.lit(1)).alias("n")), named("triangle"), "triangle"), ORACLES["count_triangle_d1"])

# Patterns and plans ---------------------------------------------------------------------------------------------


def permutations_sql(n: int) -> str:
    """All permutations as columns p0.. ."""
    tables = ", ".join(f"range({n}) t{i}(p{i})" for i in range(n))
    apart = " AND ".join(f"p{a} <> p{b}" for a, b in combinations(range(n), 2))
    return f"SELECT {', '.join(f'p{i}' for i in range(n))} FROM {tables} WHERE {apart}"


def _adjacent_sql(p: Pattern, a: str, b: str) -> str:
    return "(" + " OR ".join(f"({a} = {x} AND {b} = {y}) OR ({a} = {y} AND {b} = {x})" for x, y in p.edges) + ")"


def _text(p: Pattern, restrictions) -> str:
    return " ".join(f"{p.names[a]}>{p.names[b]}" for a, b in sorted(restrictions))


def _arrangements(spark, sf, n: int):
    """ids: of each customer with n orders or more the first n, by their dates."""
    rows = spark.read.parquet(f"{sf}/orders.parquet").where("o_custkey is not null and o_orderkey is not null and o_orderdate is not null")
    listed = rows.groupBy("o_custkey").agg(F.sort_array(F.collect_list(F.struct("o_orderdate", "o_orderkey"))).alias("x")).select(F.array_distinct("x.o_orderkey").alias("ids"))
    return listed.where(F.size("ids") >= n).select(F.slice("ids", 1, n).alias("ids"))


def _autos(n):
    """The automorphisms, and of how many customers each one brings the orders, in the places of the pattern's vertices, to their
    least arrangement: every customer's orders have one image that symmetry breaking keeps."""

    def run(spark, sf):
        p = named(n)
        group = symmetry.automorphisms(p)
        text = [",".join(map(str, a)) for a in group]
        images = F.array(*(F.struct(F.array(*(F.get("ids", F.lit(v)) for v in a)).alias("image"), F.lit(t).alias("perm")) for a, t in zip(group, text, strict=True)))
        met = _arrangements(spark, sf, p.n).select(F.array_min(images)["perm"].alias("perm")).groupBy("perm").agg(F.count(F.lit(1)).alias("met"))
        every = spark.createDataFrame([(t, len(symmetry.swaps(a))) for a, t in zip(group, text, strict=True)], "perm string, swaps long")
        return every.join(met, "perm", "left").select("perm", "swaps", F.coalesce("met", F.lit(0)).cast("long").alias("customers"))

    return run


def _autos_sql(p: Pattern) -> str:
    """The group from the pattern's edges alone; the least image of each customer's orders among the images by all of it."""
    swaps = " + ".join(f"(p{a} = {b} AND p{b} = {a})::INTEGER" for a, b in combinations(range(p.n), 2))
    group = f"SELECT concat_ws(',', {', '.join(f'p{i}' for i in range(p.n))}) AS perm, ({swaps})::BIGINT AS swaps, [{', '.join(f'p{i}' for i in range(p.n))}] AS g FROM ({permutations_sql(p.n)}) t WHERE " + " AND ".join(_adjacent_sql(p, f"p{a}", f"p{b}") for a, b in p.edges)
    image = ", ".join(f"ids[g[{i + 1}] + 1] AS i{i}" for i in range(p.n))
    return (
        f"WITH autos AS MATERIALIZED ({group}), days AS (SELECT o_custkey AS c, o_orderkey AS o, min(o_orderdate) AS day FROM orders WHERE o_custkey IS NOT NULL AND o_orderkey IS NOT NULL AND o_orderdate IS NOT NULL GROUP BY 1, 2), "
        f"tuples AS (SELECT c, list(o ORDER BY day, o) AS ids FROM days GROUP BY c HAVING count(*) >= {p.n}), images AS (SELECT c, perm, {image} FROM tuples, autos), "
        f"least AS (SELECT c, perm FROM images QUALIFY row_number() OVER (PARTITION BY c ORDER BY {', '.join(f'i{i}' for i in range(p.n))}) = 1) "
        "SELECT perm, any_value(swaps) AS swaps, count(c) AS customers FROM autos LEFT JOIN least USING (perm) GROUP BY perm"
    )


def _schedules(n):
    def run(spark, sf):
        p = named(n)
        k = schedules.efficient(p)[1]
        one = set(schedules.connected_prefix(schedules.all_orders(p), p))
        rows = [("".join(p.names[v] for v in o), o in one, o in one and schedules.independent(o[p.n - k :], p)) for o in schedules.all_orders(p)]
        return spark.createDataFrame(rows, "sched string, phase1 boolean, phase2 boolean")

    return run


def _schedules_sql(p: Pattern) -> str:
    """free is how many vertices at an order's end have no edge among them; the most over phase 1 is what phase 2 asks."""
    name = "CASE {} " + " ".join(f"WHEN {i} THEN '{x}'" for i, x in enumerate(p.names)) + " END"
    one = " AND ".join("(" + " OR ".join(_adjacent_sql(p, f"p{j}", f"p{i}") for j in range(i)) + ")" for i in range(1, p.n))
    ends = [" AND ".join(f"NOT {_adjacent_sql(p, f'p{a}', f'p{b}')}" for a, b in combinations(range(p.n - k, p.n), 2)) for k in range(2, p.n + 1)]
    free = "CASE " + " ".join(f"WHEN NOT ({e}) THEN {k}" for k, e in enumerate(ends, 1)) + f" ELSE {p.n} END"
    return (
        f"WITH o AS MATERIALIZED (SELECT concat({', '.join(name.format(f'p{i}') for i in range(p.n))}) AS sched, {one} AS phase1, {free} AS free FROM ({permutations_sql(p.n)}) t) "
        "SELECT sched, phase1, phase1 AND free >= (SELECT max(free) FROM o WHERE phase1) AS phase2 FROM o"
    )


def _sets(n):
    def run(spark, sf):
        p = named(n)
        rows = [(_text(p, s), symmetry.orders(p.n).mask(s).bit_count(), symmetry.orders(p.n).count // len(symmetry.automorphisms(p))) for s in symmetry.restriction_sets(p)]
        return spark.createDataFrame(rows, "restrictions string, kept long, expected long")

    return run


def _sets_sql(p: Pattern) -> str:
    """p_i is the rank of vertex i's id; the expected number comes from counting automorphisms the same way."""
    table = permutations_sql(p.n)
    autos = "(SELECT count(*) FROM perms WHERE " + " AND ".join(_adjacent_sql(p, f"p{a}", f"p{b}") for a, b in p.edges) + ")"
    rows = " UNION ALL ".join(f"SELECT '{_text(p, s)}' AS restrictions, count(*) AS kept, (SELECT count(*) FROM perms) // {autos} AS expected FROM perms WHERE " + " AND ".join(f"p{a} > p{b}" for a, b in sorted(s)) for s in symmetry.restriction_sets(p))
    return f"WITH perms AS MATERIALIZED ({table}) {rows}"


def _closed_sets(n):
    """All restriction sets of a pattern, with the inequalities they imply, that the program finds."""

    def run(spark, sf):
        p = named(n)
        return spark.createDataFrame([(_text(p, s),) for s in planner.distinct_sets(p)], "restrictions string")

    return run


def _closed_sets_sql(p: Pattern) -> str:
    """Every relation on the vertices that is closed and has no circle, if each order of ids has exactly one image under
    the automorphisms that satisfies it. Nothing here comes from the program but the pattern's edges."""
    pairs = [(a, b) for a in range(p.n) for b in range(p.n) if a != b]
    bit = {x: f"(m >> {i}) & 1" for i, x in enumerate(pairs)}
    closed = [f"NOT ({bit[a, b]} = 1 AND {bit[b, a]} = 1)" for a, b in combinations(range(p.n), 2)]
    closed += [f"NOT ({bit[a, b]} = 1 AND {bit[b, c]} = 1 AND {bit[a, c]} = 0)" for a, b in pairs for c in range(p.n) if c not in (a, b)]
    holds = " AND ".join(f"({bit[a, b]} = 0 OR r[g[{a + 1}] + 1] > r[g[{b + 1}] + 1])" for a, b in pairs)
    text = f"concat_ws(' ', {', '.join(f"""CASE WHEN {bit[a, b]} = 1 THEN '{p.names[a]}>{p.names[b]}' END""" for a, b in pairs)})"
    return (
        f"WITH perms AS MATERIALIZED ({permutations_sql(p.n)}), ranks AS (SELECT [{', '.join(f'p{i}' for i in range(p.n))}] AS r FROM perms), "
        f"autos AS (SELECT [{', '.join(f'p{i}' for i in range(p.n))}] AS g FROM perms WHERE {' AND '.join(_adjacent_sql(p, f'p{a}', f'p{b}') for a, b in p.edges)}), "
        f"sets AS MATERIALIZED (SELECT m FROM range({1 << len(pairs)}) t(m) WHERE {' AND '.join(closed)}), "
        f"kept AS (SELECT m, r, count(*) FILTER (WHERE {holds}) AS images FROM sets, ranks, autos GROUP BY m, r) "
        f"SELECT {text} AS restrictions FROM (SELECT m FROM kept GROUP BY m HAVING min(images) = 1 AND max(images) = 1) t"
    )


def _on_complete_graph(spark, sf):
    rows = []
    for n in ("triangle", "rectangle", "w1"):
        sets = symmetry.restriction_sets(named(n))
        rows += [(n, _text(named(n), s), ok) for s, ok in zip(sets, api.valid_on_complete_graph(spark, named(n), sets), strict=True)]
    return spark.createDataFrame(rows, "pattern string, restrictions string, valid boolean")


register(
    "validate_on_complete_graph", _on_complete_graph,
    " UNION ALL ".join(f"SELECT '{n}' AS pattern, restrictions, kept = expected AS valid FROM ({kept_sql}) u" for n, kept_sql in ((n, _sets_sql(named(n))) for n in ("triangle", "rectangle", "w1"))),
)

TYPICAL = cost_model.GraphStats(2000, 13_000, 6_400)


def _probs(n):
    def run(spark, sf):
        p = named(n)
        c = planner.choose(p, TYPICAL)
        return spark.createDataFrame([(i, p.names[v], round(f, 9)) for i, (v, f) in enumerate(zip(c.order, cost_model.filter_probs(c.order, p, c.restrictions), strict=True))], "loop long, vertex string, f double")

    return run


def _probs_sql(p: Pattern) -> str:
    c = planner.choose(p, TYPICAL)
    at = {v: i for i, v in enumerate(c.order)}
    upto = lambda i: " AND ".join([f"p{a} > p{b}" for a, b in sorted(c.restrictions) if max(at[a], at[b]) <= i] or ["true"])
    rows = " UNION ALL ".join(f"SELECT {i}::BIGINT AS loop, '{p.names[v]}' AS vertex, round(1 - count(*) FILTER (WHERE {upto(i)}) / count(*) FILTER (WHERE {upto(i - 1)}), 9) AS f FROM perms" for i, v in enumerate(c.order))
    return f"WITH perms AS MATERIALIZED ({permutations_sql(p.n)}) {rows}"


def _outer(p: Pattern):
    c = planner.choose(p, TYPICAL)
    return planner.outer_restrictions(c, min(schedules.suffix_size(c.order, p), p.n - 1))


def _overcount(n):
    def run(spark, sf):
        p = named(n)
        times = symmetry.overcount(p, _outer(p)).tolist()
        return spark.createDataFrame([(t, times.count(t)) for t in sorted(set(times))], "copies long, orders long")

    return run


def _overcount_sql(p: Pattern) -> str:
    """Of each order of ids, the automorphisms whose image of it satisfies the outer inequalities."""
    outer = _outer(p)
    tests = " + ".join("(" + " AND ".join([f"p{g[a]} > p{g[b]}" for a, b in sorted(outer)] or ["true"]) + ")::INTEGER" for g in symmetry.automorphisms(p))
    return f"SELECT copies::BIGINT AS copies, count(*) AS orders FROM (SELECT {tests} AS copies FROM ({permutations_sql(p.n)}) t) u GROUP BY copies"


def _divisor_paper(n):
    def run(spark, sf):
        p = named(n)
        return spark.createDataFrame([(planner.divisor_paper(p, _outer(p)), planner.divisor_exact(p, _outer(p)))], "printed long, exact long")

    return run


def _divisor_sql(p: Pattern) -> str:
    """printed: automorphisms under which some order of ids and its image both satisfy the outer inequalities; exact: how
    many images of an order do, where that is the same for all orders."""
    own = " AND ".join([f"p{a} > p{b}" for a, b in sorted(_outer(p))] or ["true"])
    tests = ["(" + " AND ".join([f"p{g[a]} > p{g[b]}" for a, b in sorted(_outer(p))] or ["true"]) + ")" for g in symmetry.automorphisms(p)]
    printed = " + ".join(f"(count(*) FILTER (WHERE {own} AND {t}) > 0)::BIGINT" for t in tests)
    times = " + ".join(f"{t}::BIGINT" for t in tests)
    return f"WITH perms AS MATERIALIZED ({permutations_sql(p.n)}) SELECT {printed} AS printed, CASE WHEN min({times}) = max({times}) THEN min({times}) END AS exact FROM perms"


PLANNED = [n for n in CATALOGUE if n not in ("edge", "k5")]
for _n in PLANNED:
    _p = named(_n)
    register(f"autos_{_n}", _autos(_n), _autos_sql(_p))
    register(f"overcount_{_n}", _overcount(_n), _overcount_sql(_p))
    register(f"filter_probs_{_n}", _probs(_n), _probs_sql(_p))
    if _p.n <= 6:
        register(f"divisors_{_n}", _divisor_paper(_n), _divisor_sql(_p))
    if _p.n <= 4:
        register(f"closed_sets_{_n}", _closed_sets(_n), _closed_sets_sql(_p))
    if _p.n <= 6:
        register(f"schedules_{_n}", _schedules(_n), _schedules_sql(_p))
        register(f"validate_sets_{_n}", _sets(_n), _sets_sql(_p))


def _model_cards(d):
    def run(spark, sf):
        s = graph(spark, sf, d).stats_frame()
        v, e, t = (F.col(c).cast("double") for c in ("n_vertices", "n_edges", "n_triangles"))
        p1, p2 = 2 * e / (v * v), 6 * t * v / (4 * e * e)
        return s.select(*(F.round(x, 9).alias(k) for k, x in (("p1", p1), ("p2", p2), ("card1", v * p1), ("card2", v * p1 * p2), ("card3", v * p1 * p2 * p2))))

    return run


for _d in ("d1", "d2", "d3"):
    register(
        f"model_cards_{_d}", _model_cards(_d),
        with_edges(_d, f"SELECT round(2 * m / (v * v), 9) AS p1, round(6 * t * v / (4 * m * m), 9) AS p2, round(2 * m / v, 9) AS card1, round(2 * m / v * (6 * t * v / (4 * m * m)), 9) AS card2, "
                   f"round(2 * m / v * power(6 * t * v / (4 * m * m), 2), 9) AS card3 FROM (SELECT (SELECT count(*) FROM deg)::DOUBLE AS v, (SELECT count(*) FROM e)::DOUBLE AS m, {TRIANGLES}::DOUBLE AS t) x"),
    )
def _config_costs(n, d):
    def run(spark, sf):
        p, s = named(n), graph(spark, sf, d).stats()
        rows = [("".join(p.names[v] for v in c.order), _text(p, c.restrictions), round(math.log(c.cost), 9)) for c in planner.rank(p, s)]
        return spark.createDataFrame(rows, "sched string, restrictions string, log_cost double")

    return run


def _config_costs_sql(p: Pattern, d: str) -> str:
    """The cost recursion written out for each configuration, over three counts of the edges and counts of orders."""
    rows = []
    for o in schedules.efficient(p)[0]:
        near = [[u for u in o[:i] if p.adjacent(u, v)] for i, v in enumerate(o)]
        done, work = set(), [[] for _ in o]
        for own in near:  # an intersection is taken where its last list is bound, and once for all that start with it
            for q in range(2, len(own) + 1):
                if tuple(own[:q]) not in done:
                    done.add(tuple(own[:q]))
                    work[o.index(own[q - 1])].append(f"c{q - 1} + c1")
        for s in planner.distinct_sets(p):
            kept = lambda i, o=o, s=s: " AND ".join([f"p{a} > p{b}" for a, b in sorted(s) if {a, b} <= {*o[: i + 1]}] or ["true"])
            share = [f"(SELECT (count(*) FILTER (WHERE {kept(i)}))::DOUBLE / count(*) FILTER (WHERE {kept(i - 1)}) FROM perms)" for i in range(p.n)]
            total = f"c{len(near[-1])} * {share[-1]}"
            for i in range(p.n - 2, -1, -1):
                total = f"c{len(near[i])} * {share[i]} * ({' + '.join(work[i]) or '0'} + {total})"
            rows.append(f"SELECT '{''.join(p.names[v] for v in o)}' AS sched, '{_text(p, s)}' AS restrictions, round(ln({total}), 9) AS log_cost FROM cards")
    top = max(len(a) for a in p.around)
    cards = ", ".join(f"2 * m / v * power(6 * t * v / (4 * m * m), {q - 1}) AS c{q}" for q in range(1, top + 1))
    return with_edges(d, f", perms AS MATERIALIZED ({permutations_sql(p.n)}), cards AS MATERIALIZED (SELECT v AS c0, {cards} FROM (SELECT (SELECT count(*) FROM deg)::DOUBLE AS v, (SELECT count(*) FROM e)::DOUBLE AS m, {TRIANGLES}::DOUBLE AS t) x) " + " UNION ALL ".join(rows))


for _n in ("rectangle", "diamond", "tailed", "w1"):
    register(f"config_costs_{_n}_d1", _config_costs(_n, "d1"), _config_costs_sql(named(_n), "d1"))
for _n in ("w1", "w2", "w4"):
    register(f"config_rank_{_n}_d1", lambda spark, sf, n=_n: api.explain(graph(spark, sf, "d1"), named(n)))

# Baselines ------------------------------------------------------------------------------------------------------

HEAVY = {"filter_process": ("triangle", "diamond", "rectangle"), "star_join": ("triangle", "rectangle", "w1"), "extension": ("triangle", "rectangle", "w1"), "naive": ("triangle", "rectangle", "w1")}
for _b, _run in baselines.BASELINES.items():
    for _n in HEAVY.get(_b, ("triangle", "rectangle", "w1", "w2")):
        register(f"baseline_{_b}_{_n}_d1", lambda spark, sf, f=_run, n=_n: f(graph(spark, sf, "d1"), named(n), name=n), ORACLES[f"count_{_n}_d1"])
for _f in (0, 1):
    register(f"baseline_unfiltered{_f}_w1_d1" if _f else "baseline_all_orders_rectangle_d1", lambda spark, sf, f=_f: baselines.unfiltered(graph(spark, sf, "d1"), named("w1" if f else "rectangle"), f, name="w1" if f else "rectangle"), ORACLES["count_w1_d1" if _f else "count_rectangle_d1"])
for _n, _d in (("wedge", "d2"), ("k4", "d2"), ("triangle", "d1")):
    register(f"sample_estimate_{_n}_{_d}", lambda spark, sf, n=_n, d=_d: baselines.sample_count(graph(spark, sf, d), named(n), trials=400, name=n))
