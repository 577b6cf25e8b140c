"""Graph utilities and the joins Spark lacks: range and as-of."""

from __future__ import annotations


from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import Graph, oriented
from ..sources.io import ensure_checkpoint_dir


def common_neighbours(g: Graph) -> DataFrame:
    """src, dst, common, deg_src, deg_dst of every edge."""
    adj = g.adjacency()
    a = adj.select(F.col("id").alias("src"), F.col("nbrs_n").alias("x"), F.col("deg").alias("deg_src"))
    b = adj.select(F.col("id").alias("dst"), F.col("nbrs_n").alias("y"), F.col("deg").alias("deg_dst"))
    return g.edges.join(a, "src").join(b, "dst").select("src", "dst", F.size(F.array_intersect("x", "y")).alias("common"), "deg_src", "deg_dst")


def triangles_per_vertex(g: Graph) -> DataFrame:
    """id, n of the vertices in triangles."""
    up = oriented(g)
    succ = up.groupBy("a").agg(F.collect_list("b").alias("s"))
    found = up.join(succ, "a").join(succ.select(F.col("a").alias("b"), F.col("s").alias("t")), "b").select("a", "b", F.array_intersect("s", "t").alias("c"))
    corners = found.select(F.explode(F.concat(F.transform("c", lambda x: x), F.array_repeat("a", F.size("c")), F.array_repeat("b", F.size("c")))).alias("id"))
    return corners.groupBy("id").agg(F.count(F.lit(1)).alias("n"))


def clustering(g: Graph) -> DataFrame:
    """id, c: share of a vertex's neighbour pairs that are adjacent, for vertices with two neighbours or more."""
    deg = g.adjacency().select("id", F.col("deg").cast("long").alias("deg")).where("deg > 1")
    return deg.join(triangles_per_vertex(g), "id", "left").select("id", F.round(2 * F.coalesce("n", F.lit(0)) / (F.col("deg") * (F.col("deg") - 1)), 9).alias("c"))


def k_core(g: Graph, k: int) -> DataFrame:
    """Edges among vertices that keep k neighbours after all others are taken away, round by round."""
    ensure_checkpoint_dir(g.spark)
    e = g.edges.select("src", "dst").checkpoint()
    while True:
        ends = e.select(F.col("src").alias("id")).unionByName(e.select(F.col("dst").alias("id")))
        weak = ends.groupBy("id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") < k).select("id")
        left = e.join(weak.withColumnRenamed("id", "src"), "src", "left_anti").join(weak.withColumnRenamed("id", "dst"), "dst", "left_anti").select("src", "dst").checkpoint()
        if left.count() == e.count():
            return left
        e = left


def ego_net(g: Graph, vertex: int) -> DataFrame:
    """Edges among a vertex and its neighbours."""
    near = g.adjacency().where(F.col("id") == vertex).select(F.explode(F.array_append("nbrs_n", F.col("id"))).alias("id"))
    return induced_subgraph(g, near)


def induced_subgraph(g: Graph, vertices: DataFrame) -> DataFrame:
    """Edges with both ends among ``vertices`` (id)."""
    v = vertices.select("id").distinct()
    return g.edges.select("src", "dst").join(v.withColumnRenamed("id", "src"), "src", "left_semi").join(v.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst")


def connected_components(g: Graph) -> DataFrame:
    """id, component: the smallest id reachable, direction aside. Labels spread, then jump to their label's label."""
    ensure_checkpoint_dir(g.spark)
    e = g.edges.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b"))).checkpoint()
    label = both.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.first("a")).alias("component")).checkpoint()
    while True:
        spread = both.join(label.select(F.col("id").alias("b"), F.col("component").alias("c")), "b").groupBy(F.col("a").alias("id")).agg(F.min("c").alias("c"))
        met = label.join(spread, "id").select("id", F.least("component", "c").alias("component"))
        jump = met.select(F.col("id").alias("component"), F.col("component").alias("up"))
        new = met.join(jump, "component", "left").select("id", F.coalesce("up", "component").alias("component")).checkpoint()
        if new.join(label.withColumnRenamed("component", "old"), "id").where("component <> old").isEmpty():
            return new
        label = new


def relabel_by_degree(g: Graph) -> DataFrame:
    """id, new_id: 0.. by (degree, id); partitions' sizes, one row each, give where each starts."""
    deg = g.adjacency().select("id", "deg").repartitionByRange("deg", "id").withColumn("_part", F.spark_partition_id()).persist()
    sizes = deg.groupBy("_part").agg(F.count(F.lit(1)).alias("n"))
    starts = sizes.select("_part", F.coalesce(F.sum("n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    return deg.join(F.broadcast(starts), "_part").select("id", (F.row_number().over(Window.partitionBy("_part").orderBy("deg", "id")) + F.col("start") - 1).alias("new_id"))


def range_pairs(df: DataFrame, group: str, member: str, at: str, seconds: int) -> DataFrame:
    """u < v with rows of the same group at most ``seconds`` apart: an equi-join on time buckets of that width and their neighbours."""
    micros = F.unix_micros(F.col(at).cast("timestamp"))
    width = seconds * 1_000_000
    rows = df.select(F.col(group).alias("g"), F.col(member).alias("m"), micros.alias("t")).withColumn("bucket", F.floor(F.col("t") / width)).where("t is not null")
    left = rows.select("g", F.col("m").alias("u"), F.col("t").alias("t1"), F.explode(F.array(F.col("bucket") - 1, F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    right = rows.select("g", F.col("m").alias("v"), F.col("t").alias("t2"), "bucket")
    return left.join(right, ["g", "bucket"]).where((F.col("u") < F.col("v")) & (F.abs(F.col("t1") - F.col("t2")) <= width)).select("u", "v").distinct()


def as_of(left: DataFrame, right: DataFrame, key: str, ts: str, at: str) -> DataFrame:
    """Each left row with the latest right time not after its own, by one window over both tables."""
    names = [c for c in left.columns if c not in (key, ts)]
    a = left.select(key, F.col(ts).cast("timestamp_ntz").alias("_t"), F.lit(1).alias("_side"), F.struct(*left.columns).alias("_row"), F.lit(None).cast("timestamp_ntz").alias(at))
    b = right.select(key, F.col(at).cast("timestamp_ntz").alias("_t"), F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.col(at).cast("timestamp_ntz").alias(at))
    w = Window.partitionBy(key).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(at, F.last(at, ignorenulls=True).over(w)).where("_side = 1").select(key, F.col("_t").alias(ts), *(F.col(f"_row.{n}").alias(n) for n in names), at)
