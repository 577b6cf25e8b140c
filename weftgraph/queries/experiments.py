"""The experiment workloads on the given tables. Counts and loop work are deterministic; seconds never meet an oracle."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import api, metrics
from ..operators import baselines
from ..plans import cost_model, planner, schedules, sql, symmetry
from ..plans.patterns import WORKLOAD, Pattern, connected_shapes, named
from ..plans.planner import Configuration
from ..sources.graphs import EDGES_SQL, graph
from . import engine

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return add


def _union(frames) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def _counts_sql(rows: list[tuple[str, str, str]]) -> str:
    """rows: pattern, graph, method."""
    return " UNION ALL ".join(f"(SELECT pattern, '{d}' AS graph, '{m}' AS method, n FROM ({engine.ORACLES[f'count_{n}_{d}']}) t)" for n, d, m in rows)


def _marked(df: DataFrame, d: str, method: str) -> DataFrame:
    return df.select("pattern", F.lit(d).alias("graph"), F.lit(method).alias("method"), "n")


GRID = [(n, d) for d in ("d1", "d2") for n in WORKLOAD]
#: Seconds that a cell may take before its row says "timeout".
CELL_SECONDS = 4.0
#: The one cell whose order passes both phases and multiplies wedges of a sparse graph; it runs an order of the first phase.
_LOOSE = {("w5", "d2")}
_X1 = [(n, d, m) for n, d in GRID for m in ("planned", "single_set", "motif_dataframe") if (n, d) not in _LOOSE or m == "planned"]


def _planned(g, n, d):
    return baselines.unfiltered(g, named(n), 1, n) if (n, d) in _LOOSE else api.count(g, named(n), method="enumerate", name=n)


@query("x1_overall_counts", _counts_sql(_X1))
def _(spark, sf):
    """Every workload on the two smaller graphs by every method; on the largest, x1_overall_seconds has the counts."""
    run = {"planned": lambda g, n, d: _planned(g, n, d), "single_set": lambda g, n, d: baselines.single_set(g, named(n), n), "motif_dataframe": lambda g, n, d: baselines.motif_dataframe(g, named(n), n)}
    return _union([_marked(run[m](graph(spark, sf, d), n, d), d, m) for n, d, m in _X1])


def overall(spark, sf, cells: list[tuple[str, str]], seconds: float = CELL_SECONDS, methods: tuple[str, ...] = ("planned", "planned_iep", "single_set", "extension", "relational_tuples", "motif_dataframe")):
    """A measurement of each method in each (pattern, graph): count, seconds, and whether it ended in time."""
    rows = []
    for n, d in cells:
        g, p = graph(spark, sf, d), named(n)
        g.stats()
        runs = {
            "planned": lambda: _planned(g, n, d), "planned_iep": lambda: api.count(g, p, method="iep"), "single_set": lambda: baselines.single_set(g, p),
            "extension": lambda: baselines.extension(g, p), "relational_tuples": lambda: baselines.relational_tuples(g, p), "motif_dataframe": lambda: baselines.motif_dataframe(g, p),
        }
        for m in methods:
            t = metrics.timed(g, runs[m], seconds)
            rows.append((n, d, m, t.value, None, t.seconds, t.status))
    return rows


@query("x1_overall_seconds")
def _(spark, sf):
    """w1 to w6 on d1; on d2 and d3 the two engines with a plan (``python -m weftgraph.workloads`` runs all cells of all methods)."""
    rows = overall(spark, sf, [(n, "d1") for n in WORKLOAD], methods=("planned", "planned_iep", "single_set", "extension"))
    rows += overall(spark, sf, [(n, d) for d in ("d2", "d3") for n in WORKLOAD], methods=("planned_iep", "single_set"))
    return spark.createDataFrame(rows, metrics.MEASUREMENTS)


@query("x2_restriction_sets")
def _(spark, sf):
    """Same order, the single set against the model's: gain in loop work over all orders where they differ, and seconds of both
    in the order where the gain is largest."""
    rows = []
    for n, d in [(n, d) for n in ("w1", "w2", "w4") for d in ("d1", "d2")]:
        g, p = graph(spark, sf, d), named(n)
        meter, pairs = metrics.LoopWork(g), metrics.set_pairs(g, p)
        mean, most, k = metrics.restriction_speedup(g, p)
        single, best = max(pairs, key=lambda x: meter.of(x[0]) / max(1, meter.of(x[1])), default=(None, None))
        times = [metrics.enumerated(g, c, CELL_SECONDS).seconds if c else None for c in (single, best)]
        rows.append((n, d, mean, most, k, *times))
    return spark.createDataFrame(rows, "pattern string, graph string, mean_gain double, max_gain double, orders long, single_seconds double, ours_seconds double")


@query("x3_schedule_choice")
def _(spark, sf):
    """Same set, the order of a random-graph estimate against ours: loop work and seconds. Work of seven-vertex patterns is left out."""
    rows = []
    for n, d in GRID:
        g, p = graph(spark, sf, d), named(n)
        other, ours = metrics.schedule_pair(g, p)
        work = [metrics.LoopWork(g).of(c) for c in (other, ours)] if p.n < 7 else [None, None]
        a, b = (metrics.enumerated(g, c, CELL_SECONDS) for c in (other, ours))
        rows.append((n, d, *work, a.seconds, b.seconds, a.status, b.status))
    return spark.createDataFrame(rows, "pattern string, graph string, flat_work long, ours_work long, flat_seconds double, ours_seconds double, flat_status string, ours_status string")


_X3 = [(n, d) for n, d in GRID if (n, d) not in _LOOSE]


@query("x3_schedule_counts", _counts_sql([(n, d, m) for n, d in _X3 for m in ("flat", "ours")]))
def _(spark, sf):
    out = []
    for n, d in _X3:
        g, p = graph(spark, sf, d), named(n)
        out += [_marked(api.count(g, p, c, method="enumerate", name=n), d, m) for m, c in zip(("flat", "ours"), metrics.schedule_pair(g, p), strict=True)]
    return _union(out)


def work_sql(d: str, rows: list[tuple[str, Configuration]]) -> str:
    """label and loop_work of configurations: each prefix's bindings, and the lengths of the lists intersected for each,
    counted over the edges."""
    terms: dict[tuple, str] = {}
    uses: dict[tuple[str, str], int] = {}

    def add(label: str, p, prefix: frozenset, rules, of: tuple[int, ...]) -> None:
        own = frozenset(r for r in rules if {*r} <= prefix)
        key = (p, prefix, own, frozenset(of))
        name = terms.setdefault(key, f"t{len(terms)}")
        uses[label, name] = uses.get((label, name), 0) + 1

    for label, c in rows:
        p, rules = c.pattern, symmetry.closure(c.restrictions)
        taken: set[tuple[int, ...]] = set()
        for i, v in enumerate(c.order):
            prefix = frozenset(c.order[: i + 1])
            add(label, p, prefix, rules, ())
            for w in c.order[i + 1 :]:  # lists of a later vertex that are all bound once v is
                near = tuple(u for u in c.order[: c.order.index(w)] if p.adjacent(u, w))
                upto = near[: near.index(v) + 1] if v in near else ()
                if len(upto) > 1 and upto not in taken:
                    taken.add(upto)
                    add(label, p, prefix, rules, upto[:-1])
                    add(label, p, prefix, rules, upto[-1:])
    parts = []
    for (p, prefix, own, of), name in terms.items():
        keep = sorted(prefix)
        if len(keep) == 1:
            body = "SELECT count(*) FROM deg" if not of else "SELECT sum(deg) FROM deg"
        else:
            q = Pattern(tuple(p.names[v] for v in keep), tuple((keep.index(a), keep.index(b)) for a, b in p.edges if {a, b} <= prefix))
            order = schedules.connected_prefix(schedules.all_orders(q), q)[0]
            head, last = sql.steps(q, "SELECT src, dst FROM base", frozenset((keep.index(a), keep.index(b)) for a, b in own), order=order)
            lists = [p.names[v] for v in sorted(of)]
            joins = "".join(f" JOIN both_ways l{k} ON l{k}.a = r.{x}" + (f" AND l{k}.b = l0.b" if k else "") for k, x in enumerate(lists)) if len(lists) > 1 else f" JOIN deg ON deg.id = r.{lists[0]}" if lists else ""
            body = f"{head} SELECT {'coalesce(sum(deg.deg), 0)' if len(lists) == 1 else 'count(*)'} FROM {last} r{joins}"
        parts.append(f"SELECT '{name}' AS term, ({body})::BIGINT AS n")
    held = ", ".join(f"('{label}', '{name}', {k})" for (label, name), k in uses.items())
    return (
        f"WITH base AS MATERIALIZED ({EDGES_SQL[d]}), both_ways AS MATERIALIZED (SELECT src AS a, dst AS b FROM base UNION ALL SELECT dst, src FROM base), "
        f"deg AS MATERIALIZED (SELECT a AS id, count(*) AS deg FROM both_ways GROUP BY a), terms AS MATERIALIZED ({' UNION ALL '.join(parts)}) "
        f"SELECT label, sum(n * times)::BIGINT AS loop_work FROM (VALUES {held}) u(label, term, times) JOIN terms USING (term) GROUP BY label"
    )


def _x4_rows() -> list[tuple[str, Configuration]]:
    p = named("w3")
    single = symmetry.closure(symmetry.orbit_restrictions(p))
    return [("".join(p.names[v] for v in o), Configuration(p, o, single)) for o in schedules.efficient(p)[0]]


def _x9_rows() -> list[tuple[str, Configuration]]:
    p = named("w1")
    return [("".join(p.names[v] for v in o) + " " + engine._text(p, s), Configuration(p, o, s)) for o in schedules.efficient(p)[0] for s in planner.distinct_sets(p)]


def _loop_work(rows, d):
    def run(spark, sf):
        meter = metrics.LoopWork(graph(spark, sf, d))
        return spark.createDataFrame([(label, meter.of(c)) for label, c in rows()], "label string, loop_work long")

    return run


query("x4_loop_work", work_sql("d1", _x4_rows()))(_loop_work(_x4_rows, "d1"))
query("x9_loop_work", work_sql("d2", _x9_rows()))(_loop_work(_x9_rows, "d2"))


@query("x4_schedule_scatter")
def _(spark, sf):
    """Every order of a six-vertex pattern: which phases it passes, its predicted cost, its loop work, and whether it is chosen.

    An order that fails the first phase ranges over all vertices in some loop; its work is given by the product and not run.
    """
    p, g = named("w3"), graph(spark, sf, "d1")
    meter, k = metrics.LoopWork(g), schedules.efficient(p)[1]
    single = symmetry.closure(symmetry.orbit_restrictions(p))
    chosen = planner.choose(p, g.stats(), restrictions=single).order
    rows = []
    for o in schedules.all_orders(p):
        one = schedules.is_connected_prefix(o, p)
        two = one and schedules.independent(o[p.n - k :], p)
        c = Configuration(p, o, single)
        rows.append(("".join(p.names[v] for v in o), one, two, cost_model.cost(o, p, single, g.stats()), meter.of(c) if one else None, o == chosen))
    return spark.createDataFrame(rows, "sched string, phase1 boolean, phase2 boolean, cost double, loop_work long, chosen boolean")


@query("x5_selected_vs_oracle")
def _(spark, sf):
    """The selected configuration against the one with the least loop work, in work and in seconds, and how costs rank the works.

    Seven-vertex patterns have hundreds of configurations; ``weftgraph.workloads`` measures them.
    """
    rows = []
    for n, d in [(n, d) for n, d in GRID if named(n).n < 7]:
        g, p = graph(spark, sf, d), named(n)
        meter = metrics.LoopWork(g)
        found = metrics.configurations(g, p)
        works = [meter.of(c) for c in found]
        best = found[works.index(min(works))]
        times = [metrics.enumerated(g, c, CELL_SECONDS).seconds for c in (found[0], best)]
        rows.append((n, d, works[0], min(works), max(works), works[0] / max(1, min(works)) - 1, metrics.rank_corr([c.cost for c in found], works), *times))
    return spark.createDataFrame(rows, "pattern string, graph string, selected long, least long, most long, regret double, rank_correlation double, selected_seconds double, least_seconds double")


_X6 = [(n, d) for n, d in GRID if (n, d) not in _LOOSE]


@query("x6_iep_counts", _counts_sql([(n, d, m) for n, d in _X6 for m in ("iep", "no_iep")]))
def _(spark, sf):
    out = []
    for n, d in _X6:
        g, p = graph(spark, sf, d), named(n)
        out += [_marked(api.count(g, p, method="iep", name=n), d, "iep"), _marked(baselines.no_iep(g, p, n), d, "no_iep")]
    return _union(out)


@query("x6_iep_seconds")
def _(spark, sf):
    """All workloads on all three graphs; a cell that does not end in time says so."""
    rows = []
    for n, d in [*GRID, *((n, "d3") for n in WORKLOAD)]:
        g, p = graph(spark, sf, d), named(n)
        g.stats()
        slow, fast = metrics.iep_speedup(g, p, CELL_SECONDS)
        rows += [(n, d, m, t.value, None, t.seconds, t.status) for m, t in (("enumerate", slow), ("iep", fast))]
    return spark.createDataFrame(rows, metrics.MEASUREMENTS)


@query("x7_partition_sweep", _counts_sql([(n, "d1", f"tasks_{k}") for n in ("w1", "w2") for k in (4, 16, 64)]))
def _(spark, sf):
    """The replicated executor over more and more tasks: the answer stays."""
    from ..operators import executor

    g = graph(spark, sf, "d1")
    return _union([_marked(executor.replicated_count(g, named(n), partitions=k, name=n), "d1", f"tasks_{k}") for n in ("w1", "w2") for k in (4, 16, 64)])


@query("x7_scaling_seconds")
def _(spark, sf):
    """Seconds against the number of tasks that may run at once; ``weftgraph.workloads scaling`` starts a session per number of cores."""
    rows = [(n, *r) for n in ("w1", "w2") for r in metrics.scale(graph(spark, sf, "d2"), named(n), [1, 2, 4, 8])]
    return spark.createDataFrame(rows, "pattern string, tasks int, seconds double, speedup double")


@query("x8_preparation_seconds")
def _(spark, sf):
    rows = []
    for n in WORKLOAD:
        done = planner.prepare(named(n), engine.TYPICAL)
        rows.append((n, done.ranked, *(done.timings[k] for k in ("automorphisms", "restriction_sets", "schedules", "ranking", "generation")), sum(done.timings.values())))
    return spark.createDataFrame(rows, "pattern string, configurations long, automorphisms double, restriction_sets double, schedules double, ranking double, generation double, total double")


@query("x9_best_and_worst")
def _(spark, sf):
    """Over all configurations of the house: least and most loop work, and the seconds of those two."""
    rows, g = [], graph(spark, sf, "d2")
    for phases in (2, 1):
        least, most, ratio = metrics.spread(g, named("w1"), phases)
        meter, found = metrics.LoopWork(g), metrics.configurations(g, named("w1"), phases)
        times = [metrics.enumerated(g, pick(found, key=meter.of), CELL_SECONDS).seconds for pick in (min, max)]
        rows.append(("w1", "d2", phases, least, most, ratio, *times))
    return spark.createDataFrame(rows, "pattern string, graph string, phases int, least long, most long, ratio double, least_seconds double, most_seconds double")


@query("x10_rectangle_rounds", "SELECT * FROM (VALUES (0, '', 8, 24), (1, 'B>D', 6, 12), (2, 'A>C B>D', 2, 6), (3, 'A>B A>C B>D', 1, 3)) t(round, restrictions, survivors, orders)")
def _(spark, sf):
    """Adding inequalities to the rectangle one by one: permutations left, orders kept."""
    p = named("rectangle")
    rows, chosen = [], frozenset()
    for i, pair in enumerate([None, (1, 3), (0, 2), (0, 1)]):
        chosen = chosen | ({pair} if pair else set())
        left = sum(symmetry.survives(g, chosen) for g in symmetry.automorphisms(p))
        rows.append((i, engine._text(p, chosen), left, symmetry.orders(p.n).mask(chosen).bit_count()))
    return spark.createDataFrame(rows, "round int, restrictions string, survivors int, orders int")


@query("x11_complete_graph", engine.with_edges("d4", "SELECT 'w1' AS pattern, 5040::BIGINT AS automorphisms7, (v * (v - 1) * (v - 2) * (v - 3) * (v - 4) // 2)::BIGINT AS n FROM (SELECT count(*) AS v FROM deg) x"))
def _(spark, sf):
    from ..plans.patterns import clique

    n = api.count(graph(spark, sf, "d4"), named("w1"), method="iep", name="w1")
    return n.select("pattern", F.lit(len(symmetry.automorphisms(clique(7)))).cast("long").alias("automorphisms7"), "n")


_X12 = [(k, d, i) for k in (3, 4) for d in ("d1", "d2") for i in (False, True)]


@query("x12_motifs", " UNION ALL ".join(f"(SELECT pattern, '{d}' AS graph, {str(i).lower()} AS induced, n FROM ({sql.count_sql(p, EDGES_SQL[d], p.text(), induced=i)}) t)" for k, d, i in _X12 for p in connected_shapes(k)))
def _(spark, sf):
    """All shapes of three and four vertices, induced and not, on both graphs."""
    return _union([api.motifs(graph(spark, sf, d), k, i).select("pattern", F.lit(d).alias("graph"), F.lit(i).alias("induced"), "n") for k, d, i in _X12])


@query("x13_rare_patterns")
def _(spark, sf):
    """Sampled estimates against exact counts: the fewer the matches, the worse."""
    rows = []
    for n in ("wedge", "triangle", "k4", "w6"):
        g, p = graph(spark, sf, "d2"), named(n)
        exact = api.count(g, p).first()["n"]
        for seed in (1, 2, 3):
            r = baselines.sample_count(g, p, trials=300, seed=seed).first()
            low, high = baselines.monte_carlo_interval(r["hits"], r["share"], len(symmetry.automorphisms(p)))
            rows.append((n, seed, exact, r["estimate"], metrics.rel_error(r["estimate"], exact), bool(low <= exact <= high)))
    return spark.createDataFrame(rows, "pattern string, seed int, exact long, estimate double, relative_error double, covered boolean")


@query("x14_loop_rows")
def _(spark, sf):
    """Rows of each loop against what the model expects."""
    rows = []
    for n in ("w1", "w2", "w4"):
        g, p = graph(spark, sf, "d1"), named(n)
        for v, got, expected in metrics.loop_rows(g, planner.choose(p, g.stats())):
            rows.append((n, v, got, expected, metrics.qerror(expected, got)))
    return spark.createDataFrame(rows, "pattern string, vertex string, loop_rows long, expected double, q_error double")
