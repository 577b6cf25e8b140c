"""A configuration as SQL text: the same loops as joins over an edge table, in the dialect common to Spark and DuckDB."""

from __future__ import annotations

from . import cost_model, schedules, symmetry
from .patterns import Pattern


def default_order(p: Pattern) -> schedules.Order:
    typical = cost_model.GraphStats(10_000, 60_000, 30_000)
    return min(schedules.efficient(p, phases=1)[0], key=lambda o: (cost_model.cost(o, p, symmetry.orbit_restrictions(p), typical), o))


def steps(p: Pattern, edges_sql: str, restrictions=None, induced: bool = False, order: schedules.Order | None = None, materialized: bool = True, seeds: str | None = None) -> tuple[str, str]:
    """(WITH list, name of the last table): each table binds one more vertex; ``seeds`` names a table of ids for the first one."""
    order = order or default_order(p)
    rules = symmetry.closure(symmetry.orbit_restrictions(p) if restrictions is None else restrictions)
    at = {v: i for i, v in enumerate(order)}
    word = " MATERIALIZED" if materialized else ""
    both = "SELECT src AS a, dst AS b FROM e" + ("" if p.directed else " UNION ALL SELECT dst, src FROM e")
    parts = [f"e AS{word} ({edges_sql})", f"s AS{word} ({both})", f"step0 AS (SELECT DISTINCT a AS {p.names[order[0]]} FROM {f"(SELECT id AS a FROM {seeds})" if seeds else "(SELECT a FROM s UNION ALL SELECT b FROM s)"} x)"]
    for i, v in enumerate(order[1:], 1):
        name, joins, conds = p.names[v], [], []
        where = []
        for u in order[:i]:
            for a, b in ((u, v), (v, u)):
                if (a, b) in p.edges or (not p.directed and (b, a) in p.edges and (a, b) == (u, v)):
                    mine, theirs = ("a", "b") if a == u else ("b", "a")
                    if not joins:
                        conds.append(f"x.{theirs}")
                        joins.append(f"JOIN s x ON x.{mine} = p.{p.names[u]}")
                    else:
                        where.append(f"EXISTS (SELECT 1 FROM s z WHERE z.{mine} = p.{p.names[u]} AND z.{theirs} = {{v}})")
            if not p.adjacent(u, v):
                where.append(f"{{v}} <> p.{p.names[u]}")
                if induced:
                    where.append(f"NOT EXISTS (SELECT 1 FROM s y WHERE y.a = p.{p.names[u]} AND y.b = {{v}})")
        where += [f"p.{p.names[a]} > {{v}}" for a, b in sorted(rules) if b == v and at[a] < i] + [f"{{v}} > p.{p.names[b]}" for a, b in sorted(rules) if a == v and at[b] < i]
        last = i == p.n - 1
        parts.append(
            f"step{i} AS{'' if last else word} (SELECT p.*, {conds[0]} AS {name} FROM step{i - 1} p {' '.join(joins)}"
            + (" WHERE " + " AND ".join(w.format(v=conds[0]) for w in where) if where else "") + ")"
        )
    return "WITH " + ", ".join(parts), f"step{p.n - 1}"


def count_sql(p: Pattern, edges_sql: str, name: str, restrictions=None, induced: bool = False, divisor: int = 1) -> str:
    head, last = steps(p, edges_sql, restrictions, induced)
    return f"{head} SELECT '{name}' AS pattern, (count(*){f' // {divisor}' if divisor > 1 else ''})::BIGINT AS n FROM {last}"


def match_sql(p: Pattern, edges_sql: str) -> str:
    """edge_key of every subgraph."""
    head, last = steps(p, edges_sql)
    pair = (lambda a, b: f"{{'a': {a}, 'b': {b}}}") if p.directed else (lambda a, b: f"{{'a': least({a}, {b}), 'b': greatest({a}, {b})}}")
    pairs = ", ".join(pair(p.names[a], p.names[b]) for a, b in p.edges)
    return f"{head} SELECT array_to_string(list_transform(list_sort([{pairs}]), lambda pair_: pair_.a || '-' || pair_.b), ' ') AS edge_key FROM {last}"
