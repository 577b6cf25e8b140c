"""Queries over single operators: scans, joins, aggregates, windows, arrays, sources, sinks and functions on the graphs."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import udfs
from ..operators import graph_ops
from ..operators.baselines import tuple_bytes
from ..plans.patterns import named
from ..sources import io
from ..sources.graphs import EDGES_SQL, TARGET_OFFSET, from_edges, graph, in_classes, line_stars
from . import engine
from .engine import with_edges

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return add


_EDGE_SQL = EDGES_SQL["d1"]


def d1(rest: str) -> str:
    return with_edges("d1", rest)


def table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def edges(spark, sf, d="d1") -> DataFrame:
    return graph(spark, sf, d).edges.select("src", "dst")


def both(spark, sf, d="d1") -> DataFrame:
    e = edges(spark, sf, d)
    return e.select(F.col("src").alias("a"), F.col("dst").alias("b")).unionByName(e.select(F.col("dst").alias("a"), F.col("src").alias("b")))


def degrees(spark, sf, d="d1") -> DataFrame:
    return graph(spark, sf, d).adjacency().select("id", F.col("deg").cast("long").alias("deg"))


# Scans and joins ------------------------------------------------------------------------------------------------


@query("op_scan_project_filter", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_returnflag = 'R' AND l_shipdate >= TIMESTAMP '1995-01-01' AND l_quantity BETWEEN 10 AND 20")
def _(spark, sf):
    return table(spark, sf, "lineitem").where("l_returnflag = 'R' and l_shipdate >= timestamp_ntz '1995-01-01' and l_quantity between 10 and 20").select("l_orderkey", "l_partkey")


@query("op_self_theta_join", "SELECT a.l_partkey AS u, b.l_partkey AS v, count(*) AS n FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey WHERE a.l_returnflag = 'R' AND b.l_returnflag = 'R' GROUP BY 1, 2")
def _(spark, sf):
    r = table(spark, sf, "lineitem").where("l_returnflag = 'R'")
    return r.select("l_orderkey", F.col("l_partkey").alias("u")).join(r.select("l_orderkey", F.col("l_partkey").alias("v")), "l_orderkey").where("u < v").groupBy("u", "v").agg(F.count(F.lit(1)).alias("n"))


for _name, _hint in (("op_broadcast_join", "broadcast"), ("op_sort_merge_join", "merge"), ("op_shuffle_hash_join", "shuffle_hash")):

    @query(_name, d1("SELECT p.p_brand AS brand, count(*) AS n FROM s JOIN part p ON p.p_partkey = s.a GROUP BY 1"))
    def _(spark, sf, hint=_hint):
        # parts: as large as the catalogue of parts; the hint is what this query shows
        return both(spark, sf).join(table(spark, sf, "part").select(F.col("p_partkey").alias("a"), F.col("p_brand").alias("brand")).hint(hint), "a").groupBy("brand").agg(F.count(F.lit(1)).alias("n"))


@query("op_nested_loop_join", "SELECT a.n_name AS x, b.n_name AS y FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_nationkey > b.n_nationkey")
def _(spark, sf):
    n = table(spark, sf, "nation")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, F.expr("a.n_regionkey < b.n_regionkey and a.n_nationkey > b.n_nationkey")).select(F.col("a.n_name").alias("x"), F.col("b.n_name").alias("y"))


@query("op_cross_complete_graph", "SELECT a.s_suppkey AS src, b.s_suppkey AS dst FROM supplier a, supplier b WHERE a.s_suppkey < b.s_suppkey AND a.s_suppkey <= 40 AND b.s_suppkey <= 40")
def _(spark, sf):
    s = table(spark, sf, "supplier").where("s_suppkey <= 40")
    return s.select(F.col("s_suppkey").alias("src")).crossJoin(s.select(F.col("s_suppkey").alias("dst"))).where("src < dst")


@query("op_semi_edge_exists", d1("SELECT x.b AS u, x.a AS mid, y.b AS v FROM s x JOIN s y ON x.a = y.a AND x.b < y.b WHERE EXISTS (SELECT 1 FROM e WHERE e.src = x.b AND e.dst = y.b)"))
def _(spark, sf):
    s = both(spark, sf)
    w = s.select(F.col("a").alias("mid"), F.col("b").alias("u")).join(s.select(F.col("a").alias("mid"), F.col("b").alias("v")), "mid").where("u < v")
    return w.join(edges(spark, sf).toDF("u", "v"), ["u", "v"], "left_semi").select("u", "mid", "v")


@query("op_anti_open_wedge", d1("SELECT x.a AS mid, count(*) AS n FROM s x JOIN s y ON x.a = y.a AND x.b < y.b WHERE NOT EXISTS (SELECT 1 FROM e WHERE e.src = x.b AND e.dst = y.b) GROUP BY 1"))
def _(spark, sf):
    s = both(spark, sf)
    w = s.select(F.col("a").alias("mid"), F.col("b").alias("u")).join(s.select(F.col("a").alias("mid"), F.col("b").alias("v")), "mid").where("u < v")
    return w.join(edges(spark, sf).toDF("u", "v"), ["u", "v"], "left_anti").groupBy("mid").agg(F.count(F.lit(1)).alias("n"))


@query("op_left_isolated", d1("SELECT p_partkey AS id FROM part LEFT JOIN deg ON id = p_partkey WHERE deg IS NULL"))
def _(spark, sf):
    return table(spark, sf, "part").select(F.col("p_partkey").alias("id")).join(degrees(spark, sf), "id", "left").where("deg is null").select("id")


@query("op_full_outer_degrees", f"WITH x AS ({d1('SELECT id, deg FROM deg')}), y AS ({with_edges('d2', 'SELECT id, deg FROM deg')}) SELECT coalesce(x.id, y.id) AS id, coalesce(x.deg, 0) AS d1, coalesce(y.deg, 0) AS d2 FROM x FULL JOIN y ON x.id = y.id")
def _(spark, sf):
    x, y = degrees(spark, sf).toDF("id", "d1"), degrees(spark, sf, "d2").toDF("id", "d2")
    return x.join(y, "id", "full").select("id", F.coalesce("d1", F.lit(0)).alias("d1"), F.coalesce("d2", F.lit(0)).alias("d2"))


@query("op_range_join_coactive", "SELECT DISTINCT a.user_id AS u, b.user_id AS v FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id < b.user_id AND abs(date_diff('microsecond', a.ts, b.ts)) <= 60000000")
def _(spark, sf):
    return graph_ops.range_pairs(table(spark, sf, "events"), "event_type", "user_id", "ts", 60)


@query("op_asof_last_order", "SELECT e.event_id, max(o.o_orderdate) AS last_order FROM events e LEFT JOIN orders o ON o.o_custkey = e.user_id AND o.o_orderdate <= e.ts GROUP BY 1")
def _(spark, sf):
    return graph_ops.as_of(table(spark, sf, "events").select("event_id", F.col("user_id").alias("key"), "ts"), table(spark, sf, "orders").select(F.col("o_custkey").alias("key"), F.col("o_orderdate").alias("at")), "key", "ts", "at").select("event_id", F.col("at").alias("last_order"))


@query("op_lateral_explode", d1("SELECT a AS id, b AS nbr, row_number() OVER (PARTITION BY a ORDER BY b) - 1 AS pos FROM s WHERE a <= 50"))
def _(spark, sf):
    return graph(spark, sf, "d1").adjacency().where("id <= 50").select("id", F.posexplode("nbrs_n").alias("pos", "nbr")).select("id", "nbr", F.col("pos").cast("long").alias("pos"))


# Aggregates -----------------------------------------------------------------------------------------------------


@query("op_group_having", d1("SELECT a AS id, count(*) AS n FROM s GROUP BY a HAVING count(*) >= 20"))
def _(spark, sf):
    return both(spark, sf).groupBy(F.col("a").alias("id")).agg(F.count(F.lit(1)).alias("n")).where("n >= 20")


@query("op_distinct_agg", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps, bool_and(l_quantity > 0) AS pos, arg_max(l_partkey, l_extendedprice) AS top FROM lineitem GROUP BY 1")
def _(spark, sf):
    """top: of the parts at the highest price the smallest, which is the same for every order of the rows."""
    rows = table(spark, sf, "lineitem")
    aggs = rows.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps"), F.bool_and(F.col("l_quantity") > 0).alias("pos"))
    priced = rows.where("l_partkey is not null and l_extendedprice is not null")
    dearest = priced.groupBy(F.col("l_returnflag").alias("flag")).agg(F.max("l_extendedprice").alias("most"))
    tops = priced.join(dearest, F.col("l_returnflag").eqNullSafe(F.col("flag")) & (F.col("l_extendedprice") == F.col("most"))).groupBy("flag").agg(F.min("l_partkey").alias("top"))
    return aggs.join(tops, F.col("l_returnflag").eqNullSafe(F.col("flag")), "left").drop("flag")


@query("op_approx_distinct")
def _(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.01).alias("parts"))


_LABELLED = "SELECT p.p_brand AS brand, p.p_type AS kind FROM s JOIN part p ON p.p_partkey = s.a"


def labelled(spark, sf):
    return both(spark, sf).join(table(spark, sf, "part").select(F.col("p_partkey").alias("a"), F.col("p_brand").alias("brand"), F.col("p_type").alias("kind")), "a")


@query("op_rollup_labels", d1(f"SELECT brand, kind, count(*) AS n FROM ({_LABELLED}) t GROUP BY ROLLUP (brand, kind)"))
def _(spark, sf):
    return labelled(spark, sf).rollup("brand", "kind").agg(F.count(F.lit(1)).alias("n"))


@query("op_cube_labels", d1(f"SELECT brand, kind, count(*) AS n FROM ({_LABELLED}) t GROUP BY CUBE (brand, kind)"))
def _(spark, sf):
    return labelled(spark, sf).cube("brand", "kind").agg(F.count(F.lit(1)).alias("n"))


@query("op_grouping_sets_labels", d1(f"SELECT brand, kind, count(*) AS n FROM ({_LABELLED}) t GROUP BY GROUPING SETS ((brand), (kind), ())"))
def _(spark, sf):
    return labelled(spark, sf).groupingSets([["brand"], ["kind"], []], "brand", "kind").agg(F.count(F.lit(1)).alias("n"))


@query("op_pivot_event_type", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY 1")
def _(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).fillna(0)


@query("op_percentiles_degree", d1("SELECT quantile_cont(deg, 0.5) AS p50, quantile_cont(deg, 0.9) AS p90, quantile_cont(deg, 0.99) AS p99 FROM deg"))
def _(spark, sf):
    return degrees(spark, sf).agg(*(F.percentile("deg", q).alias(k) for k, q in (("p50", 0.5), ("p90", 0.9), ("p99", 0.99))))


# Windows, sorting, sets -----------------------------------------------------------------------------------------


@query("op_rank_neighbours", d1("SELECT a, b, row_number() OVER w AS rn, rank() OVER k AS rk, dense_rank() OVER k AS dr FROM s JOIN deg ON deg.id = s.b WINDOW w AS (PARTITION BY a ORDER BY deg DESC, b), k AS (PARTITION BY a ORDER BY deg DESC)"))
def _(spark, sf):
    r = both(spark, sf).join(degrees(spark, sf).toDF("b", "deg"), "b")
    k = Window.partitionBy("a").orderBy(F.desc("deg"))
    return r.select("a", "b", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("deg"), "b")).cast("long").alias("rn"), F.rank().over(k).cast("long").alias("rk"), F.dense_rank().over(k).cast("long").alias("dr"))


@query("op_ntile_degree", d1("SELECT id, ntile(4) OVER (PARTITION BY id % 10 ORDER BY deg, id) AS q FROM deg"))
def _(spark, sf):
    return degrees(spark, sf).select("id", F.ntile(4).over(Window.partitionBy(F.col("id") % 10).orderBy("deg", "id")).cast("long").alias("q"))


@query("op_lag_turns", "SELECT conv_id, turn, lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS before, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS who FROM conversations")
def _(spark, sf):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return table(spark, sf, "conversations").select("conv_id", "turn", F.lag("turn").over(w).alias("before"), F.lag("role").over(w).alias("who"))


@query("op_lead_events", "SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM events")
def _(spark, sf):
    return table(spark, sf, "events").select("event_id", F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("nxt"))


@query("op_running_offsets", d1("SELECT a, b, count(*) OVER (PARTITION BY a ORDER BY b ROWS UNBOUNDED PRECEDING) AS upto FROM s"))
def _(spark, sf):
    return both(spark, sf).select("a", "b", F.count(F.lit(1)).over(Window.partitionBy("a").orderBy("b").rowsBetween(Window.unboundedPreceding, 0)).alias("upto"))


@query("op_range_frame_events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM (SELECT *, date_trunc('second', ts) AS t2 FROM events) q")
def _(spark, sf):
    e = table(spark, sf, "events").withColumn("s", F.round(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long"))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("n"))


@query("op_topk_per_vertex", d1("SELECT a, b FROM s JOIN deg ON deg.id = s.b QUALIFY row_number() OVER (PARTITION BY a ORDER BY deg DESC, b) <= 3"))
def _(spark, sf):
    r = both(spark, sf).join(degrees(spark, sf).toDF("b", "deg"), "b")
    return r.withColumn("rn", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("deg"), "b"))).where("rn <= 3").select("a", "b")


@query("op_global_topk", d1("SELECT id, deg FROM deg ORDER BY deg DESC, id LIMIT 25"))
def _(spark, sf):
    return degrees(spark, sf).orderBy(F.desc("deg"), "id").limit(25)


@query("op_topk_triangle_vertices", d1("SELECT v AS id, count(*) AS n FROM (SELECT unnest([x.src, x.dst, y.dst]) AS v FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst) t GROUP BY v ORDER BY n DESC, id LIMIT 20"))
def _(spark, sf):
    return graph_ops.triangles_per_vertex(graph(spark, sf, "d1")).orderBy(F.desc("n"), "id").limit(20)


@query("op_topk_edges_by_support", d1("SELECT e.src, e.dst, (SELECT count(*) FROM s x JOIN s y ON x.b = y.b WHERE x.a = e.src AND y.a = e.dst) AS support FROM e ORDER BY support DESC, src, dst LIMIT 20"))
def _(spark, sf):
    return graph_ops.common_neighbours(graph(spark, sf, "d1")).select("src", "dst", F.col("common").cast("long").alias("support")).orderBy(F.desc("support"), "src", "dst").limit(20)


_E3 = with_edges("d3", "SELECT src, dst FROM e")
_E1 = d1("SELECT src, dst FROM e")
for _name, _sql, _run in (
    ("op_union_all", f"SELECT * FROM ({_E1}) x UNION ALL SELECT * FROM ({_E3}) y", lambda a, b: a.unionByName(b)),
    ("op_union_distinct", f"SELECT * FROM ({_E1}) x UNION SELECT * FROM ({_E3}) y", lambda a, b: a.union(b).distinct()),
    ("op_intersect", f"SELECT * FROM ({_E1}) x INTERSECT SELECT * FROM ({_E3}) y", lambda a, b: a.intersect(b)),
    ("op_intersect_all", f"SELECT * FROM ({_E1}) x INTERSECT ALL SELECT * FROM ({_E3}) y", lambda a, b: a.intersectAll(b)),
    ("op_except", f"SELECT * FROM ({_E3}) x EXCEPT SELECT * FROM ({_E1}) y", lambda a, b: b.subtract(a)),
    ("op_except_all", f"SELECT * FROM ({_E3}) x EXCEPT ALL SELECT * FROM ({_E1}) y", lambda a, b: b.exceptAll(a)),
):

    @query(_name, _sql)
    def _(spark, sf, run=_run):
        return run(edges(spark, sf), edges(spark, sf, "d3"))


# Arrays, maps, text, dates, numbers -----------------------------------------------------------------------------

_COMMON = "(SELECT count(*) FROM s x JOIN s y ON x.b = y.b WHERE x.a = e.src AND y.a = e.dst)"


@query("op_array_common_neighbours", d1(f"SELECT src, dst, {_COMMON}::INTEGER AS common FROM e"))
def _(spark, sf):
    return graph_ops.common_neighbours(graph(spark, sf, "d1")).select("src", "dst", "common")


@query("op_array_except_bound", d1("SELECT a AS id, count(*)::INTEGER AS n FROM s WHERE b > a GROUP BY a"))
def _(spark, sf):
    adj = graph(spark, sf, "d1").adjacency()
    upper = F.slice("nbrs_n", F.size(F.array_except("nbrs_n", F.array_union("nbrs_n", F.array("id")))) + 1, F.size("nbrs_n"))
    return adj.select("id", F.explode(upper).alias("b")).where("b > id").groupBy("id").agg(F.count(F.lit(1)).cast("int").alias("n"))


@query("op_jaccard", d1(f"SELECT src, dst, round({_COMMON} / (x.deg + y.deg - {_COMMON}), 9) AS jaccard FROM e JOIN deg x ON x.id = src JOIN deg y ON y.id = dst"))
def _(spark, sf):
    return graph_ops.common_neighbours(graph(spark, sf, "d1")).select("src", "dst", F.round(F.col("common") / (F.col("deg_src") + F.col("deg_dst") - F.col("common")), 9).alias("jaccard"))


@query("op_array_hof", d1("SELECT a AS id, sum(b)::BIGINT AS total, count(*) FILTER (WHERE b % 2 = 0) AS even, bool_or(b > 1900) AS high, max(b) AS top FROM s GROUP BY a"))
def _(spark, sf):
    n = F.col("nbrs_n")
    return graph(spark, sf, "d1").adjacency().select("id", F.aggregate(n, F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.size(F.filter(n, lambda x: x % 2 == 0)).cast("long").alias("even"), F.exists(n, lambda x: x > 1900).alias("high"), F.element_at(n, -1).alias("top"))


@query("op_map_degree_lookup", "SELECT n_name, (SELECT count(*) FROM nation m WHERE m.n_regionkey = n.n_regionkey)::INTEGER AS same_region FROM nation n")
def _(spark, sf):
    n = table(spark, sf, "nation")
    sizes = n.groupBy("n_regionkey").agg(F.count(F.lit(1)).cast("int").alias("k")).agg(F.map_from_entries(F.collect_list(F.struct("n_regionkey", "k"))).alias("m"))  # five regions
    return n.crossJoin(F.broadcast(sizes)).select("n_name", F.element_at("m", F.col("n_regionkey")).alias("same_region"))


@query("op_json_props_graph", "SELECT json_extract_string(props, '$.k') AS k, count(DISTINCT user_id) AS users, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf):
    return table(spark, sf, "events").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.countDistinct("user_id").alias("users"), F.count(F.lit(1)).alias("n"))


@query("op_string_href", "SELECT u.target, count(DISTINCT page_id) AS pages FROM pages, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS u(target) GROUP BY 1")
def _(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target")).groupBy("target").agg(F.countDistinct("page_id").alias("pages"))


@query("op_string_lines", "SELECT md5(line) AS line, count(DISTINCT doc_id) AS docs FROM (SELECT doc_id, trim(u.l, ' ') AS line FROM documents, unnest(string_split(text, chr(10))) AS u(l)) t WHERE length(line) >= 20 GROUP BY 1 HAVING count(DISTINCT doc_id) > 1")
def _(spark, sf):
    lines = table(spark, sf, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("l")).select("doc_id", F.trim("l").alias("line")).where(F.length("line") >= 20)
    return lines.groupBy(F.md5("line").alias("line")).agg(F.countDistinct("doc_id").alias("docs")).where("docs > 1")


@query("op_contains_bench", "SELECT b.item_id, count(*) AS docs FROM benchmark b JOIN documents d ON contains(d.text, substr(b.text, 1, 60)) GROUP BY 1")
def _(spark, sf):
    items = table(spark, sf, "benchmark").select("item_id", F.substring("text", 1, 60).alias("start"))
    return table(spark, sf, "documents").join(items, F.contains("text", "start")).groupBy("item_id").agg(F.count(F.lit(1)).alias("docs"))


@query("op_contains_bench_all")
def _(spark, sf):
    return graph(spark, sf, "d13_all").edges.groupBy((F.col("dst") - TARGET_OFFSET).alias("item_id")).agg(F.count(F.lit(1)).alias("docs"))


@query("op_date_trunc_graph", "SELECT date_trunc('hour', ts) AS slot, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def _(spark, sf):
    return table(spark, sf, "events").groupBy(F.date_trunc("hour", "ts").alias("slot")).agg(F.countDistinct("user_id").alias("users")).withColumn("slot", F.col("slot").cast("timestamp_ntz"))


@query("op_date_diff_orders", "SELECT o_custkey, date_diff('day', min(o_orderdate)::DATE, max(o_orderdate)::DATE)::INTEGER AS days FROM orders GROUP BY 1")
def _(spark, sf):
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.datediff(F.max("o_orderdate"), F.min("o_orderdate")).alias("days"))


@query("op_math_canonical_edge", d1("SELECT least(a, b) AS lo, greatest(a, b) AS hi, count(*) AS n, max((a * 31 + b) % 7) AS slot FROM s GROUP BY 1, 2"))
def _(spark, sf):
    return both(spark, sf).groupBy(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")).agg(F.count(F.lit(1)).alias("n"), F.max(F.pmod(F.col("a") * 31 + F.col("b"), F.lit(7))).alias("slot"))


def cosine_pairs(vectors: DataFrame) -> DataFrame:
    """u, v, c: the rounded cosine of each pair of vectors with the same label."""
    dot = lambda p, q: F.aggregate(F.zip_with(p, q, lambda x, y: x * y), F.lit(0.0), lambda s, t: s + t)
    v = vectors.select("label", F.col("vec_id").alias("u"), F.col("embedding").cast("array<double>").alias("x"))
    w = v.select("label", F.col("u").alias("v"), F.col("x").alias("y"))
    return v.join(w, "label").where("u < v").select("u", "v", F.round(dot("x", "y") / F.sqrt(dot("x", "x") * dot("y", "y")), 6).alias("c"))


@query("op_cosine_pairs", "SELECT a.vec_id AS u, b.vec_id AS v, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS c FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id < b.vec_id WHERE a.label = 3")
def _(spark, sf):
    return cosine_pairs(table(spark, sf, "embeddings").where("label = 3"))


@query("op_cosine_pairs_all")
def _(spark, sf):
    return cosine_pairs(table(spark, sf, "embeddings"))


# Subqueries -----------------------------------------------------------------------------------------------------


def _views(spark, sf):
    edges(spark, sf).createOrReplaceTempView("graph_edges")
    graph(spark, sf, "d1").adjacency().createOrReplaceTempView("graph_adj")


@query("op_scalar_subquery_p1", d1("SELECT round(2.0 * (SELECT count(*) FROM e) / ((SELECT count(*) FROM deg)::DOUBLE ^ 2), 12) AS p1"))
def _(spark, sf):
    _views(spark, sf)
    return spark.sql("SELECT round(2.0D * (SELECT count(*) FROM graph_edges) / pow((SELECT count(*) FROM graph_adj), 2), 12) AS p1")


@query("op_correlated_exists", d1("SELECT src, dst FROM e WHERE EXISTS (SELECT 1 FROM deg WHERE deg.id = e.src AND deg.deg > 20)"))
def _(spark, sf):
    _views(spark, sf)
    return spark.sql("SELECT src, dst FROM graph_edges e WHERE EXISTS (SELECT 1 FROM graph_adj a WHERE a.id = e.src AND a.deg > 20)")


@query("op_in_subquery", d1("SELECT src, dst FROM e WHERE src IN (SELECT id FROM deg WHERE deg > 20) AND dst NOT IN (SELECT id FROM deg WHERE deg > 10)"))
def _(spark, sf):
    _views(spark, sf)
    return spark.sql("SELECT src, dst FROM graph_edges WHERE src IN (SELECT id FROM graph_adj WHERE deg > 20) AND dst NOT IN (SELECT id FROM graph_adj WHERE deg > 10)")


def _recursive(d: str) -> str:
    return with_edges(d, "").replace("WITH e AS", "WITH RECURSIVE e AS").rstrip() + ", r(id, comp) AS (SELECT DISTINCT a, a FROM s UNION SELECT s.b, r.comp FROM r JOIN s ON s.a = r.id) SELECT id, min(comp) AS comp FROM r GROUP BY id"


@query("op_recursive_cc", _recursive("d11"))
def _(spark, sf):
    both(spark, sf, "d11").createOrReplaceTempView("graph_both")
    hops = 8  # the forest's diameter is 2
    return spark.sql(f"WITH RECURSIVE r(id, comp, k) AS (SELECT DISTINCT a, a, 0 FROM graph_both UNION ALL SELECT b.b, r.comp, r.k + 1 FROM r JOIN graph_both b ON b.a = r.id WHERE r.k < {hops}) SELECT id, min(comp) AS comp FROM r GROUP BY id")


@query("op_house_sql_text", None)
def _(spark, sf):
    from ..plans import sql

    g, p = graph(spark, sf, "d1"), named("w1")
    g.edges.select("src", "dst").createOrReplaceTempView("graph_edges")

    def run(own):
        if own is not None:
            g.degrees().select("id").where(own).createOrReplaceTempView("graph_seeds")
        head, last = sql.steps(p, "SELECT src, dst FROM graph_edges", materialized=False, seeds=None if own is None else "graph_seeds")
        return spark.sql(f"{head} SELECT count(*) AS n FROM {last}")

    return in_classes(g, tuple_bytes(g, p, sql.default_order(p)), run, "n long", tuples=True).select(F.lit("w1").alias("pattern"), "n")


ORACLES["op_house_sql_text"] = engine.ORACLES["count_w1_d1"]

# Graph operators ------------------------------------------------------------------------------------------------


def _peeled(k: int, rounds: int) -> str:
    """SQL of so many rounds of taking away vertices with fewer than k neighbours."""
    parts = [f"r0 AS MATERIALIZED (SELECT src, dst FROM ({_EDGE_SQL}) t)"]
    for i in range(rounds):
        strong = f"SELECT v FROM (SELECT src AS v FROM r{i} UNION ALL SELECT dst FROM r{i}) u GROUP BY v HAVING count(*) >= {k}"
        parts.append(f"r{i + 1} AS MATERIALIZED (SELECT src, dst FROM r{i} WHERE src IN ({strong}) AND dst IN ({strong}))")
    return f"WITH {', '.join(parts)} SELECT src, dst FROM r{rounds}"


@query("op_kcore3", _peeled(3, 12))
def _(spark, sf):
    return graph_ops.k_core(graph(spark, sf, "d1"), 3)


@query("op_clustering", d1(f"SELECT d.id, round(2.0 * coalesce(t.n, 0) / (d.deg * (d.deg - 1)), 9) AS c FROM deg d LEFT JOIN (SELECT v AS id, count(*) AS n FROM (SELECT unnest([x.src, x.dst, y.dst]) AS v FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst) q GROUP BY v) t ON t.id = d.id WHERE d.deg > 1"))
def _(spark, sf):
    return graph_ops.clustering(graph(spark, sf, "d1"))


@query("op_ego_net", d1("SELECT src, dst FROM e WHERE (src = 7 OR src IN (SELECT b FROM s WHERE a = 7)) AND (dst = 7 OR dst IN (SELECT b FROM s WHERE a = 7))"))
def _(spark, sf):
    return graph_ops.ego_net(graph(spark, sf, "d1"), 7)


@query("op_induced_subgraph", d1("SELECT src, dst FROM e JOIN part p ON p.p_partkey = src AND p.p_size <= 10 JOIN part q ON q.p_partkey = dst AND q.p_size <= 10"))
def _(spark, sf):
    return graph_ops.induced_subgraph(graph(spark, sf, "d1"), table(spark, sf, "part").where("p_size <= 10").select(F.col("p_partkey").alias("id")))


@query("op_connected_components", _recursive("d9"))
def _(spark, sf):
    return graph_ops.connected_components(graph(spark, sf, "d9")).select("id", F.col("component").alias("comp"))


@query("op_connected_components_d9_all")
def _(spark, sf):
    return graph_ops.connected_components(from_edges(line_stars(spark, sf))).select("id", F.col("component").alias("comp"))


@query("op_connected_components_d12", _recursive("d12"))
def _(spark, sf):
    return graph_ops.connected_components(graph(spark, sf, "d12")).select("id", F.col("component").alias("comp"))


@query("op_relabel_by_degree", d1("SELECT id, row_number() OVER (ORDER BY deg, id) - 1 AS new_id FROM deg"))
def _(spark, sf):
    return graph_ops.relabel_by_degree(graph(spark, sf, "d1"))


@query("op_sample_hash", d1("SELECT src, dst FROM e WHERE (src * 2654435761 + dst * 40503) % 1000 < 100"))
def _(spark, sf):
    return edges(spark, sf).where(F.pmod(F.col("src") * 2654435761 + F.col("dst") * 40503, F.lit(1000)) < 100)


@query("op_sample_bernoulli")
def _(spark, sf):
    return edges(spark, sf).sample(0.1, seed=3)


@query("op_sample_by_label")
def _(spark, sf):
    return table(spark, sf, "part").sampleBy("p_type", {t: 0.2 for t in ("PROMO", "STANDARD", "SMALL", "MEDIUM", "LARGE", "ECONOMY")}, seed=3).select("p_partkey", "p_type")


# Sources and sinks ----------------------------------------------------------------------------------------------

_EDGE_ROWS = d1("SELECT src, dst FROM e")
for _format in ("csv", "json", "orc", "parquet", "text"):

    @query(f"op_{_format}_roundtrip", _EDGE_ROWS)
    def _(spark, sf, kind=_format):
        path = io.scratch(spark, f"edges-{kind}")
        io.write_edges(edges(spark, sf), path, kind)
        return io.read_edges(spark, path, kind)


@query("op_adjacency_text_roundtrip", _EDGE_ROWS)
def _(spark, sf):
    path = io.scratch(spark, "adjacency")
    io.write_adjacency_text(graph(spark, sf, "d1"), path)
    return io.read_adjacency_text(spark, path).edges.select("src", "dst")


@query("op_partitioned_write", d1("SELECT src, dst, src % 8 AS bucket FROM e WHERE src % 8 = 3"))
def _(spark, sf):
    path = io.scratch(spark, "partitioned")
    io.write_partitioned(edges(spark, sf), path, 8)
    return spark.read.parquet(path).where("bucket = 3").select("src", "dst", F.col("bucket").cast("long").alias("bucket"))


@query("op_bucketed_table", d1("SELECT a AS id, count(*) AS deg FROM s GROUP BY a"))
def _(spark, sf):
    name = f"adjacency_{uuid.uuid4().hex[:12]}"
    io.save_bucketed(graph(spark, sf, "d1"), name, 8)
    return spark.table(name).select("id", F.col("deg").cast("long").alias("deg"))


# Functions ------------------------------------------------------------------------------------------------------

_PAIR_SUM = d1("SELECT src, dst, least(src, dst) * 1000003 + greatest(src, dst) AS code FROM e")


@query("op_udf_scalar", _PAIR_SUM)
def _(spark, sf):
    return edges(spark, sf).select("src", "dst", udfs.edge_code("src", "dst").alias("code"))


@query("op_pandas_udf", _PAIR_SUM)
def _(spark, sf):
    return edges(spark, sf).select("src", "dst", udfs.edge_code_vectorized("src", "dst").alias("code"))


@query("op_map_in_arrow", d1("SELECT a AS id, count(*) FILTER (WHERE b > a) AS higher FROM s GROUP BY a"))
def _(spark, sf):
    return udfs.higher_neighbours(graph(spark, sf, "d1").adjacency().select("id", "nbrs_n"))


@query("op_apply_in_pandas", d1("SELECT t.v AS id, count(*) AS n FROM (SELECT unnest([x.src, x.dst, y.dst]) AS v FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst) t GROUP BY 1"))
def _(spark, sf):
    return udfs.local_triangles(graph(spark, sf, "d1"))


@query("op_pandas_udaf", "SELECT l_returnflag, round(avg(l_quantity), 6) AS mean FROM lineitem GROUP BY 1")
def _(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.round(udfs.mean_of("l_quantity"), 6).alias("mean"))


@query("op_udtf_restrictions", "SELECT * FROM (VALUES (0, 'A', 'B'), (1, 'B', 'A'), (2, 'D', 'E'), (3, 'E', 'D')) t(set_id, hi, lo)")
def _(spark, sf):
    udfs.register(spark)
    return spark.sql("SELECT set_id, hi, lo FROM restriction_sets('A-B, A-C, B-C, A-D, B-E') ORDER BY set_id")


@query("op_udtf_schedules", "SELECT 16::BIGINT AS kept, 60::BIGINT AS connected, 120::BIGINT AS every")
def _(spark, sf):
    udfs.register(spark)
    return spark.sql("SELECT count_if(phase2) AS kept, count_if(phase1) AS connected, count(*) AS every FROM pattern_schedules('A-B, A-C, B-D, C-D, A-E, B-E')")


@query("op_udtf_automorphisms", "SELECT 8::BIGINT AS n, 2 AS swaps")
def _(spark, sf):
    udfs.register(spark)
    return spark.sql("SELECT count(*) AS n, max(size(array_distinct(swaps))) AS swaps FROM automorphisms('A-B, B-C, C-D, A-D')")
