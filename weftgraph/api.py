"""Matching and counting."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators import dense, iep
from .operators import executor as executors
from .plans import compiler, planner, symmetry
from .plans.patterns import Pattern, clique, connected_shapes
from .plans.planner import Configuration
from .sources.graphs import Graph, in_classes


#: Partitions a core of the first vertex's rows, where all that comes of a row stays in its task.
DEALT = 16


def edge_key(p: Pattern) -> F.Column:
    """The subgraph's own name: its edges, sorted; the same whichever copy was kept."""
    ends = [(F.col(p.names[a]), F.col(p.names[b])) for a, b in p.edges]
    pairs = [F.struct(a.alias("a"), b.alias("b")) if p.directed else F.struct(F.least(a, b).alias("a"), F.greatest(a, b).alias("b")) for a, b in ends]
    flat = F.transform(F.array_sort(F.array(*pairs)), lambda e: F.concat(e["a"].cast("string"), F.lit("-"), e["b"].cast("string")))
    return F.array_join(flat, " ")


def _configuration(g: Graph, p: Pattern, config: Configuration | None, distinct: bool) -> Configuration:
    if config is None:
        config = planner.choose(p, g.stats()) if distinct else planner.choose(p, g.stats(), restrictions=frozenset())
    return config if distinct else replace(config, restrictions=frozenset())


def match(g: Graph, p: Pattern, config: Configuration | None = None, distinct: bool = True, induced: bool = False, hint: str | None = None, limit: int | None = None, seeds: F.Column | None = None, executor: str = "auto") -> DataFrame:
    """One row per subgraph (or per mapping, if not ``distinct``), a column per pattern vertex.

    induced: keep only those with no further edge among their vertices. hint: as in compiler.emit. executor: "lists" carries
    neighbour lists in rows, "spread" cuts them into chunks, "auto" takes the latter on a graph with hubs where it can.
    """
    c = _configuration(g, p, config, distinct)
    if executor == "spread" or executor == "auto" and _may_spread(p, induced, seeds) and executors.has_hubs(g):
        rows = executors.spread(g, c).select(*p.names)
        return rows.limit(limit) if limit is not None else rows
    rows = compiler.emit(g, c, compiler.loop_plan(c, induced=induced), hint, seeds).select(*p.names)
    return rows.limit(limit) if limit is not None else rows


def _may_spread(p: Pattern, induced: bool, seeds) -> bool:
    return not (p.directed or p.vlabels or p.elabels or induced) and seeds is None


def exists(g: Graph, p: Pattern) -> bool:
    return not match(g, p, limit=1).isEmpty()


def count(g: Graph, p: Pattern, config: Configuration | None = None, method: str = "auto", induced: bool = False, distinct: bool = True, hint: str | None = None, wide: bool = False, form: str = "partitions", seed_batches: int = 1, name: str | None = None, executor: str = "auto") -> DataFrame:
    """One row: pattern and n.

    method: "enumerate" runs all loops, the last one as the size of its candidates where it has no inequality;
    "iep" leaves the independent last loops to inclusion-exclusion; "auto" takes the latter where the model finds it no dearer.
    seed_batches: run that many jobs over hash classes of the first vertex, to bound what is in flight at once.
    executor: as in match(), or "replicated"; both others than "lists" enumerate.
    """
    if executor == "replicated":
        return executors.replicated_count(g, p, config, name=name)
    if executor == "spread" or executor == "auto" and method != "iep" and distinct and _may_spread(p, induced, None) and executors.has_hubs(g):
        return executors.spread_count(g, p, config, name=name)
    if seed_batches > 1:
        total = None
        for b in range(seed_batches):
            row = _count(g, p, config, method, induced, distinct, hint, wide, form, F.pmod(F.xxhash64("id"), F.lit(seed_batches)) == b).first()
            total = row["n"] + (total or 0)
        out = g.spark.createDataFrame([(total,)], f"n {'decimal(38,0)' if wide else 'long'}")
    else:
        out = _count(g, p, config, method, induced, distinct, hint, wide, form, None)
    return out.select(F.lit(name or p.text()).alias("pattern"), "n")


def _count(g, p, config, method, induced, distinct, hint, wide, form, seeds) -> DataFrame:
    kind = "decimal(38,0)" if wide else "long"
    plain = not induced and not p.vlabels and distinct
    if method in ("auto", "iep") and plain:
        c = config if config is not None and config.iep_k else planner.with_iep(config) if config is not None else planner.choose_iep(p, g.stats())
        if method == "iep" or config is not None or c.cost <= planner.choose(p, g.stats()).cost:
            return iep_count(g, c, hint, wide, form, seeds)
    elif method == "iep":
        raise ValueError("inclusion-exclusion counts distinct, unlabelled, non-induced matches only")
    c = _configuration(g, p, config, distinct)
    plan = compiler.loop_plan(c, induced=induced)
    last = plan[-1]
    if last.above or last.below or last.barred or last.lists or (p.vlabels and p.vlabels[last.vertex] is not None):
        return _in_parts(g, c, plan, hint, seeds, lambda rows: rows.agg(F.count(F.lit(1)).cast(kind).alias("n")), f"n {kind}")
    return _summed(g, c, 1, c.restrictions, hint, wide, "partitions", seeds, induced).select(F.col("s").alias("n"))


def _summed(g: Graph, c: Configuration, k: int, restrictions, hint, wide: bool, form: str, seeds, induced: bool = False) -> DataFrame:
    """One row, s: the tuples that the last k loops would bind, over all bindings of the loops before."""
    arrays, sizes = iep.kept(c, k, form)
    plan = compiler.loop_plan(c, c.pattern.n - k, restrictions, induced, arrays, sizes)
    kind = "decimal(38,0)" if wide else "long"
    total = lambda rows: iep.count_steps(rows, c, k, form, wide).agg(F.coalesce(F.sum("tuples"), F.lit(0)).cast(kind).alias("s"))
    return _in_parts(g, c, plan, hint, seeds, total, f"s {kind}")


def _in_parts(g: Graph, c: Configuration, plan: list[compiler.Loop], hint: str | None, seeds, total, schema: str) -> DataFrame:
    """One row, the ``total`` of the plan's rows: in one job with the lists replicated where they are small, else by classes of the
    first vertex where too much would be shuffled at once."""
    if seeds is not None:
        return total(compiler.emit(g, c, plan, hint, seeds, prune=True))
    if hint is None and compiler.replicable(g, plan):
        return total(compiler.emit(g, c, plan, "broadcast", prune=True, deal=DEALT * g.spark.sparkContext.defaultParallelism))
    return in_classes(g, compiler.in_flight(g, plan), lambda own: total(compiler.emit(g, c, plan, hint, own, prune=True)), schema)


def iep_count(g: Graph, c: Configuration, hint: str | None = None, wide: bool = False, form: str = "partitions", seeds=None) -> DataFrame:
    kind = "decimal(38,0)" if wide else "long"
    summed = _summed(g, c, c.iep_k, c.outer, hint, wide, form, seeds)
    d = F.lit(c.divisor).cast(kind)
    return summed.select(F.when(F.col("s") % d == 0, (F.col("s") / d).cast(kind) if wide else F.expr(f"s div {c.divisor}")).otherwise(F.raise_error(F.lit("the count is not a multiple of its divisor"))).cast(kind).alias("n"))


def cliques(g: Graph, k: int, **more) -> DataFrame:
    """Number of k-cliques: one total order of their ids, or products of blocks where the graph is dense."""
    p = clique(k)
    if k > 2 and set(more) <= {"name"} and dense.is_dense(g):
        return dense.block_cliques(g, k).select(F.lit(more.get("name") or p.text()).alias("pattern"), "n")
    c = Configuration(p, tuple(range(k)), symmetry.closure(frozenset(zip(range(k), range(1, k), strict=False))))
    return count(g, p, c, method="enumerate", **more)


def motifs(g: Graph, k: int, induced: bool = False) -> DataFrame:
    """A row per connected shape on k vertices, with its count."""
    return reduce(DataFrame.unionByName, [count(g, p, induced=induced) for p in connected_shapes(k)])


def explain(g: Graph, p: Pattern, top: int = 20) -> DataFrame:
    """The cheapest configurations: rank, order, restrictions, cost."""
    rows = [(i + 1, *c.names(), c.cost) for i, c in enumerate(planner.rank(p, g.stats())[:top])]
    return g.spark.createDataFrame(rows, "rank int, `order` array<string>, restrictions array<string>, cost double")


def validate_on_complete_graph(spark, p: Pattern, restrictions) -> bool:
    """Count with and without the inequalities on the complete graph of as many vertices: the former must be the latter
    divided by the number of automorphisms."""
    return valid_on_complete_graph(spark, p, [restrictions])[0]


def valid_on_complete_graph(spark, p: Pattern, sets) -> list[bool]:
    """The same for many sets: one plan, a row each."""
    from .sources.graphs import from_edges

    ids = spark.range(p.n)
    g = from_edges(ids.select(F.col("id").alias("src")).crossJoin(ids.select(F.col("id").alias("dst"))).where("src < dst"))
    found = match(g, p, Configuration(p, tuple(range(p.n)), frozenset()), distinct=False, executor="lists")
    tests = [reduce(lambda a, b: a & b, [F.col(p.names[a]) > F.col(p.names[b]) for a, b in s], F.lit(True)) for s in sets]
    every, *kept = found.agg(F.count(F.lit(1)), *(F.count_if(t) for t in tests)).first()
    return [n * len(symmetry.automorphisms(p)) == every for n in kept]
