"""Data graphs: how they are held, and those the experiments build from the given tables."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.ids import dense_ids
from ..plans.cost_model import GraphStats


#: Bytes of lists that the jobs of a count may have in their rows at once.
IN_FLIGHT = 256 << 20
#: The same for joins of plain edges, which pass every open path on.
TUPLES_IN_FLIGHT = 4 << 30


@dataclass
class Graph:
    """edges: src, dst (src < dst if undirected), distinct, no loops, no nulls; with elabel where edges have labels.

    labels: id, label, one row a vertex at most.
    """

    edges: DataFrame
    directed: bool = False
    labels: DataFrame | None = None
    name: str = "graph"
    _tables: dict = field(default_factory=dict, repr=False)
    _stats: GraphStats | None = field(default=None, repr=False)
    _max_degree: int | None = field(default=None, repr=False)
    _moments: tuple[int, int] | None = field(default=None, repr=False)

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def adjacency(self, kinds: tuple[tuple[str, str | None], ...] = (("n", None),)) -> DataFrame:
        """id, deg, a sorted neighbour array per kind ("n" any, "o" out, "i" in; edge label), and label if there are.

        Arrays are named as column_of() says. Kept in memory and on disk, hash-partitioned by id, so that joins on
        the id read it where it lies.
        """
        if kinds not in self._tables:
            marks = [c for c in self.edges.columns if c == "elabel"]
            out = self.edges.select(F.col("src").alias("id"), F.col("dst").alias("nbr"), *marks, F.lit("o").alias("way"))
            both = out.unionByName(self.edges.select(F.col("dst").alias("id"), F.col("src").alias("nbr"), *marks, F.lit("i").alias("way")))
            aggs = []
            for way, mark in kinds:
                ok = F.lit(True) if way == "n" else F.col("way") == way
                if mark is not None:
                    ok &= F.col("elabel") == mark
                aggs.append(F.sort_array(F.collect_set(F.when(ok, F.col("nbr")))).alias(column_of(way, mark)))
            table = both.groupBy("id").agg(F.size(F.collect_set("nbr")).alias("deg"), *aggs)
            if self.labels is not None:
                table = table.join(self.labels.select("id", "label"), "id", "left")
            self._tables[kinds] = table.persist(StorageLevel.MEMORY_AND_DISK)
        return self._tables[kinds]

    def degrees(self) -> DataFrame:
        """id, deg: counted from the edges, so that no list is gathered. Kept like adjacency()."""
        if "degrees" not in self._tables:
            both = self.edges.select(F.col("src").alias("id"), F.col("dst").alias("nbr")).unionByName(self.edges.select(F.col("dst").alias("id"), F.col("src").alias("nbr")))
            if self.directed or "elabel" in self.edges.columns:  # a pair may have several edges
                both = both.distinct()
            self._tables["degrees"] = both.groupBy("id").agg(F.count(F.lit(1)).cast("int").alias("deg")).persist(StorageLevel.MEMORY_AND_DISK)
        return self._tables["degrees"]

    def max_degree(self) -> int:
        if self._max_degree is None:
            self._max_degree = self.degrees().agg(F.coalesce(F.max("deg"), F.lit(0))).first()[0]
        return self._max_degree

    def moments(self) -> tuple[int, int]:
        """The sum of all degrees and of their squares."""
        if self._moments is None:
            deg = F.col("deg").cast("long")
            self._moments = tuple(self.degrees().agg(F.coalesce(F.sum(deg), F.lit(0)), F.coalesce(F.sum(deg * deg), F.lit(0))).first())
        return self._moments

    def chunks(self, size: int) -> DataFrame:
        """id, deg, chunk, salt, nbrs: neighbour lists in rows of about ``size`` (nbr, its degree), each row under several salts.

        A list is dealt over its chunks by hash before it is gathered, so no task sees a whole hub. A vertex with c
        chunks has about the square root of c salts, by which those who look it up spread over tasks.
        """
        if ("chunks", size) not in self._tables:
            both = self.edges.select(F.col("src").alias("id"), F.col("dst").alias("nbr")).unionByName(self.edges.select(F.col("dst").alias("id"), F.col("src").alias("nbr"))).distinct()
            deg = self.degrees()
            ends = both.join(deg.select("id", "deg"), "id").join(deg.select(F.col("id").alias("nbr"), F.col("deg").alias("nd")), "nbr")
            dealt = ends.withColumn("chunk", F.pmod(F.xxhash64("nbr"), chunk_count(F.col("deg"), size)).cast("int"))
            rows = dealt.groupBy("id", "deg", "chunk").agg(F.collect_list(F.struct("nbr", "nd")).alias("nbrs"))
            rows = rows.select("id", "deg", "chunk", F.explode(F.sequence(F.lit(0), salt_count(F.col("deg"), size) - 1)).alias("salt"), "nbrs")
            self._tables["chunks", size] = rows.persist(StorageLevel.MEMORY_AND_DISK)
        return self._tables["chunks", size]

    def stats(self) -> GraphStats:
        """Three counts in one row; computed once."""
        if self._stats is None:
            row = self.stats_frame().first()
            self._stats = GraphStats(row["n_vertices"], row["n_edges"], row["n_triangles"])
        return self._stats

    def stats_frame(self) -> DataFrame:
        """One row: n_vertices, n_edges, n_triangles."""
        v = self.degrees().agg(F.count(F.lit(1)).alias("n_vertices"))
        e = self.edges.agg(F.count(F.lit(1)).alias("n_edges"))
        return v.crossJoin(e).crossJoin(triangle_count(self))  # three single rows

    def unpersist(self) -> None:
        """Release everything that is kept, the edges too; what is used again is made again."""
        for t in self._tables.values():
            t.unpersist()
        self._tables.clear()
        self.edges.unpersist()


def chunk_count(deg: Column, size: int) -> Column:
    return F.ceil(deg / F.lit(size)).cast("int")


def salt_count(deg: Column, size: int) -> Column:
    return F.ceil(F.sqrt(chunk_count(deg, size))).cast("int")


def column_of(way: str, mark: str | None) -> str:
    return f"nbrs_{way}" + (f"_{mark}" if mark is not None else "")


def normalize(df: DataFrame, src: str = "src", dst: str = "dst", directed: bool = False) -> DataFrame:
    """Distinct edges without loops and nulls; undirected ones as (smaller, larger)."""
    a, b = F.col(src), F.col(dst)
    ends = (a, b) if directed else (F.least(a, b), F.greatest(a, b))
    marks = [c for c in df.columns if c == "elabel"]
    return df.where(a.isNotNull() & b.isNotNull() & (a != b)).select(ends[0].cast("long").alias("src"), ends[1].cast("long").alias("dst"), *marks).distinct()


def from_edges(df: DataFrame, src: str = "src", dst: str = "dst", directed: bool = False, labels: DataFrame | None = None, name: str = "graph") -> Graph:
    return Graph(normalize(df, src, dst, directed), directed, labels, name)


def from_adjacency(df: DataFrame, vertex: str = "id", neighbours: str = "nbrs", **more) -> Graph:
    """From rows that list a vertex's neighbours."""
    return from_edges(df.select(F.col(vertex).alias("src"), F.explode(neighbours).alias("dst")), **more)


def from_keys(df: DataFrame, src: str, dst: str, **more) -> tuple[Graph, DataFrame]:
    """From edges between keys of any type; also the dictionary (key, id)."""
    keys = dense_ids(df.select(F.col(src).alias("key")).unionByName(df.select(F.col(dst).alias("key"))), "key").persist()
    a, b = (keys.select(F.col("key").alias(c), F.col("id").alias(f"_{c}")) for c in ("src", "dst"))
    ends = df.select(F.col(src).alias("src"), F.col(dst).alias("dst")).join(a, "src").join(b, "dst")
    return from_edges(ends.select(F.col("_src").alias("src"), F.col("_dst").alias("dst")), **more), keys


def _ranked(g: Graph) -> DataFrame:
    """a, b, db: edges from the end with fewer neighbours to the other, ties by id, and the neighbours of b."""
    deg = g.degrees()
    e = g.edges.join(deg.select(F.col("id").alias("src"), F.col("deg").alias("ds")), "src").join(deg.select(F.col("id").alias("dst"), F.col("deg").alias("dd")), "dst")
    up = (F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") < F.col("dst")))
    return e.select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("a"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("b"), F.when(up, F.col("dd")).otherwise(F.col("ds")).alias("db"))


def oriented(g: Graph) -> DataFrame:
    """Edges from the end with fewer neighbours to the other, ties by id: no vertex has many successors."""
    return _ranked(g).select("a", "b")


def first_row(df: DataFrame):
    """The only row of ``df``; the shuffle files of its query are given back at once."""
    conf, key = df.sparkSession.conf, "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = conf.get(key, "false")
    conf.set(key, "true")
    try:
        return df.select("*").first()
    finally:
        conf.set(key, before)


def may_replicate(size: float) -> bool:
    """Whether a table of ``size`` bytes goes to every task whole, rather than rows of many times its size to it."""
    return size <= IN_FLIGHT // 2


def in_classes(g: Graph, size: float, run, schema: str, key: str = "id", tuples: bool = False) -> DataFrame:
    """One row of one number: ``run(None)``, or where ``size`` bytes are over IN_FLIGHT (TUPLES_IN_FLIGHT for ``tuples``) the sum of ``run`` over as many hash classes
    of ``key``, one job each, whose shuffle files are given back before the next."""
    bound = TUPLES_IN_FLIGHT if tuples else IN_FLIGHT
    classes = int(min(-(-size // bound), max(1, g.stats().n_vertices))) if size > bound else 1
    if classes == 1:
        return run(None)
    total = sum(first_row(run(F.pmod(F.xxhash64(key), F.lit(classes)) == k))[0] for k in range(classes))
    return g.spark.createDataFrame([(total,)], schema)


def twin_triangle_count(members: DataFrame, in_flight: int = IN_FLIGHT) -> DataFrame:
    """One row, n_triangles, of the graph whose vertices are linked if they share a list: ``members`` has id, line.

    Vertices in just the same lists have the same neighbours and each other, so they stand as one with their number m; pairs
    are made of these only, and triangles within one, over two and over three of them weigh what they stand for.
    """
    own = members.where("id is not null").select("id", F.md5(F.col("line").cast("binary")).alias("line")).distinct()
    sets = own.groupBy("id").agg(F.sort_array(F.collect_list("line")).alias("lines"))
    kinds = sets.groupBy("lines").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("m")).persist(StorageLevel.MEMORY_AND_DISK)
    g = from_edges(_pairs(kinds.select("id", F.explode("lines").alias("line")), ["line"], "id"))
    g.edges = g.edges.persist(StorageLevel.MEMORY_AND_DISK)
    m = kinds.select("id", "m")
    e = g.edges.join(m.toDF("src", "x"), "src").join(m.toDF("dst", "y"), "dst")
    one = m.agg(F.coalesce(F.sum(F.expr("m * (m - 1) * (m - 2) div 6")), F.lit(0)).alias("one"))
    two = e.agg(F.coalesce(F.sum(F.expr("x * y * (x + y - 2) div 2")), F.lit(0)).alias("two"))
    n = first_row(triangle_count(g, in_flight, m))[0] + first_row(one)[0] + first_row(two)[0]
    g.unpersist()
    kinds.unpersist()
    return members.sparkSession.createDataFrame([(n,)], "n_triangles long")


def triangle_count(g: Graph, in_flight: int = IN_FLIGHT, weights: DataFrame | None = None) -> DataFrame:
    """One row, n_triangles: successors that both ends of an oriented edge share; with ``weights`` (id, m) the sum of their products.

    The end b of an edge gets those successors of a that come after b in the order, if there are any. Where these lists
    are over ``in_flight`` bytes the vertices are taken in so many hash classes, one job each, whose shuffle files are given back.
    A dense graph is counted by products of blocks of its adjacency matrix instead (operators/dense.py).
    """
    from ..operators import dense

    if weights is None and dense.is_dense(g):
        return dense.block_cliques(g, 3).select(F.col("n").alias("n_triangles"))
    if "successors" not in g._tables:
        up = _ranked(g)
        up = up.join(weights.toDF("b", "m"), "b").join(weights.toDF("a", "ma"), "a") if weights is not None else up.select("*", F.lit(1).alias("m"), F.lit(1).alias("ma"))
        succ = up.groupBy("a", "ma").agg(F.sort_array(F.collect_list(F.struct("db", "b", "m"))).alias("x"))
        s = F.transform("x", lambda v: F.struct(v["b"].alias("b"), v["m"].alias("m"))) if weights is not None else F.col("x.b")
        g._tables["successors"] = succ.select("a", "ma", s.alias("s")).persist(StorageLevel.MEMORY_AND_DISK)
    succ = g._tables["successors"]
    size, width = F.size("s").cast("long"), 4 if weights is None else 16
    sent = succ.agg(F.coalesce(F.sum(size * (size - 1) * width), F.lit(0)).alias("n")).first()["n"]
    classes = max(1, -(-sent // in_flight))

    def counted(which: int) -> DataFrame:
        own = succ.where(F.size("s") > 1)
        if classes > 1:
            own = own.where(F.pmod(F.xxhash64("a"), F.lit(classes)) == which)
        asks = own.select("ma", "s", F.posexplode("s").alias("i", "b")).where(F.col("i") < F.size("s") - 1)
        asks = asks.select(*(["b"] if weights is None else [F.col("b.b").alias("b"), (F.col("ma") * F.col("b.m")).alias("mm")]), F.slice("s", F.col("i") + 2, F.size("s")).alias("rest"))
        ends = succ.select(F.col("a").alias("b"), F.col("s").alias("t"))
        pairs = asks.join(ends.hint("shuffle_hash") if classes > 1 else ends, "b")
        both = F.array_intersect("rest", "t")
        met = F.size(both) if weights is None else F.aggregate(both, F.lit(0).cast("long"), lambda n, v: n + v["m"]) * F.col("mm")
        return pairs.agg(F.coalesce(F.sum(met), F.lit(0)).cast("long").alias("n_triangles"))

    if classes == 1:
        return counted(0)
    return g.spark.createDataFrame([(sum(first_row(counted(k))[0] for k in range(classes)),)], "n_triangles long")


# Graphs of the given tables. Each builder returns unnormalised pairs; the SQL beside it is the oracle's.

SUPPLIER_OFFSET, TARGET_OFFSET, TURN_STEP = 1_000_000_000, 1_000_000, 1000
LINE_CHARS, LINE_DOCS, LEAK_CHARS, KNN = 20, 50, 60, 8
#: Words of a run that a benchmark item and a document share in d13_all; a shorter item is one run.
LEAK_WORDS = 8


def _pairs(df: DataFrame, key: list[str], vertex: str) -> DataFrame:
    """All pairs (u < v) of different vertices under one key."""
    rows = df.select(*key, F.col(vertex).alias("src")).distinct()
    return rows.join(rows.withColumnRenamed("src", "dst"), key).where("src < dst").select("src", "dst")


def _first_pairs(df: DataFrame, key: list[str], vertex: str) -> DataFrame:
    """As _pairs, each pair once: under the first of the keys that both ends have, so that no pair is shuffled. A row carries the
    earlier keys of its vertex, which suits vertices with few keys under keys with many vertices."""
    rows = df.select(F.struct(*key).alias("key"), F.col(vertex).cast("long").alias("src"), *key).na.drop(subset=["src", *key]).select("key", "src").distinct()
    listed = rows.join(dense_ids(rows.select("key"), "key"), "key").groupBy("src").agg(F.sort_array(F.collect_list(F.col("id").cast("int"))).alias("ids"))
    under = listed.select("src", F.posexplode("ids").alias("at", "id"), "ids").select("src", "id", F.slice("ids", F.lit(1), F.col("at")).alias("before"))
    pairs = under.join(under.toDF("dst", "id", "others"), "id").where((F.col("src") < F.col("dst")) & ~F.arrays_overlap("before", "others"))
    return pairs.select("src", "dst")


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _co_return(spark, d):
    return _pairs(_table(spark, d, "lineitem").where("l_returnflag = 'R'"), ["l_orderkey"], "l_partkey")


def _cust_peer(spark, d):
    rows = _table(spark, d, "lineitem").join(_table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return _pairs(rows, ["l_partkey", "l_quantity"], "o_custkey")


def _co_purchase(spark, d):
    return _pairs(_table(spark, d, "lineitem"), ["l_orderkey"], "l_partkey")


def _supp_pair(spark, d):
    return _pairs(_table(spark, d, "lineitem"), ["l_orderkey"], "l_suppkey")


def _part_supp(spark, d):
    return _table(spark, d, "lineitem").select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + SUPPLIER_OFFSET).alias("dst"))


def _co_active(unit, pairs=_pairs):
    def build(spark, d):
        return pairs(_table(spark, d, "events").withColumn("slot", F.date_trunc(unit, "ts")), ["event_type", "slot"], "user_id")

    return build


def _vec_knn(spark, d):
    v = _table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("x"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda s, t: s + t)
    v = v.withColumn("norm", F.sqrt(dot(F.col("x"), F.col("x"))))
    w = v.select(F.col("id").alias("id2"), F.col("x").alias("x2"), F.col("norm").alias("norm2"))
    pairs = v.join(w, F.col("id") != F.col("id2")).select("id", "id2", (dot(F.col("x"), F.col("x2")) / (F.col("norm") * F.col("norm2"))).alias("c"))
    best = pairs.groupBy("id").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.round("c", 9)).alias("c"), "id2"))), 1, KNN).alias("b"))
    return best.select(F.col("id").alias("src"), F.explode("b.id2").alias("dst"))


def shared_lines(spark: SparkSession, d: str, most: int | None = None) -> DataFrame:
    """id, line: the trimmed lines that two documents or more hold, ``most`` at most."""
    lines = _table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.explode(F.split("text", "\n")).alias("line")).select("id", F.trim("line").alias("line"))
    lines = lines.where(F.length("line") >= LINE_CHARS).distinct()
    usual = lines.groupBy("line").agg(F.count(F.lit(1)).alias("n")).where("n >= 2" if most is None else f"n between 2 and {most}").select("line")
    return lines.join(usual, "line")


def _doc_line(most):
    def build(spark, d):
        return _pairs(shared_lines(spark, d, most), ["line"], "id")

    return build


def line_stars(spark: SparkSession, d: str) -> DataFrame:
    """Edges from the smallest document of each shared line to its others: d9_all's components in rows linear in its lines."""
    lines = shared_lines(spark, d)
    return lines.join(lines.groupBy("line").agg(F.min("id").alias("src")), "line").where("src < id").select("src", F.col("id").alias("dst"))


def page_links(spark, d):
    hrefs = _table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target")).distinct()
    return hrefs.join(dense_ids(hrefs, "target", TARGET_OFFSET), "target").select(F.col("page_id").alias("src"), F.col("id").alias("dst"))


def _nation_region(spark, d):
    return _table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("src"), (F.col("n_regionkey").cast("long") + TARGET_OFFSET).alias("dst"))


def _turn_chain(spark, d):
    turns = _table(spark, d, "conversations").select("conv_id", "turn")
    nxt = turns.select("conv_id", (F.col("turn") - 1).alias("turn"))
    at = F.col("conv_id") * TURN_STEP + F.col("turn")
    return turns.join(nxt, ["conv_id", "turn"]).select(at.alias("src"), (at + 1).alias("dst"))


def _bench_leak(spark, d):
    items = _table(spark, d, "benchmark").select((F.col("item_id") + TARGET_OFFSET).alias("dst"), F.substring("text", 1, LEAK_CHARS).alias("start"))
    docs = _table(spark, d, "documents").select(F.col("doc_id").alias("src"), "text")
    return docs.join(items, F.contains("text", "start")).select("src", "dst")


def _word_runs(df: DataFrame, vertex: str) -> DataFrame:
    """vertex, run: each LEAK_WORDS words in a row, lower-cased and with single spaces; a shorter text is one run."""
    words = F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "")
    runs = F.expr(f"transform(sequence(1, greatest(1, size(words) - {LEAK_WORDS - 1})), i -> array_join(slice(words, i, {LEAK_WORDS}), ' '))")
    return df.select(vertex, words.alias("words")).where(F.size("words") > 0).select(vertex, F.explode(runs).alias("run")).distinct()


def _bench_runs(spark, d):
    items = _word_runs(_table(spark, d, "benchmark").select((F.col("item_id") + TARGET_OFFSET).alias("dst"), "text"), "dst")
    whole = items.where(F.size(F.split("run", " ")) >= LEAK_WORDS)
    docs = _table(spark, d, "documents").select(F.col("doc_id").alias("src"), "text")
    brief = items.where(F.size(F.split("run", " ")) < LEAK_WORDS)  # an item of few words stands anywhere in a text
    flat = docs.select("src", F.concat(F.lit(" "), F.trim(F.regexp_replace(F.lower("text"), r"\s+", " ")), F.lit(" ")).alias("flat"))
    held = flat.join(brief, F.contains("flat", F.concat(F.lit(" "), "run", F.lit(" ")))).select("src", "dst")
    return _word_runs(docs, "src").join(whole, "run").select("src", "dst").unionByName(held)


BUILDERS = {
    "d1": _co_return, "d2": _cust_peer, "d3": _co_purchase, "d4": _supp_pair, "d5": _part_supp, "d6": _co_active("minute"), "d7": _co_active("hour", _first_pairs),
    "d8": _vec_knn, "d9": _doc_line(LINE_DOCS), "d10": page_links, "d11": _nation_region, "d12": _turn_chain, "d13": _bench_leak,
    "d9_all": _doc_line(None), "d13_all": _bench_runs,
}
DIRECTED = {"d10", "d12"}
#: Graphs whose builders return each edge once.
SINGLE = {"d7"}


def _labels(spark: SparkSession, d: str, name: str) -> DataFrame | None:
    if name == "d8":
        return _table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("label").cast("string").alias("label"))
    if name in ("d9", "d9_all"):
        return _table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("label"))
    if name in ("d1", "d3"):
        return _table(spark, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_brand").alias("label"))
    return None


def edge_list(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """src, dst of a graph for one reading: made anew and not kept unless the graph already is."""
    if name in SINGLE and (spark.sparkContext.applicationId, sf_dir, name) not in _built:
        return BUILDERS[name](spark, sf_dir)
    return graph(spark, sf_dir, name).edges.select("src", "dst")


_built: dict[tuple[str, str, str], Graph] = {}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A graph of the given tables; built once per application."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _built:
        make = Graph if name in SINGLE else from_edges
        g = make(BUILDERS[name](spark, sf_dir), directed=name in DIRECTED, labels=_labels(spark, sf_dir, name), name=name)
        g.edges = g.edges.persist(StorageLevel.MEMORY_AND_DISK)
        _built[key] = g
    return _built[key]


def release(spark: SparkSession) -> None:
    """Forget and unpersist all graphs built in this application."""
    for key in [k for k in _built if k[0] == spark.sparkContext.applicationId]:
        _built.pop(key).unpersist()


def _pairs_sql(rows: str, key: str) -> str:
    on = " AND ".join(f"a.{k} = b.{k}" for k in key.split(", "))
    return f"WITH r AS (SELECT DISTINCT {key}, v FROM ({rows}) t) SELECT DISTINCT a.v AS src, b.v AS dst FROM r a JOIN r b ON {on} WHERE a.v < b.v"


EDGES_SQL = {
    "d1": _pairs_sql("SELECT l_orderkey, l_partkey AS v FROM lineitem WHERE l_returnflag = 'R'", "l_orderkey"),
    "d2": _pairs_sql("SELECT l_partkey, l_quantity, o_custkey AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey", "l_partkey, l_quantity"),
    "d3": _pairs_sql("SELECT l_orderkey, l_partkey AS v FROM lineitem", "l_orderkey"),
    "d4": _pairs_sql("SELECT l_orderkey, l_suppkey AS v FROM lineitem", "l_orderkey"),
    "d5": f"SELECT DISTINCT l_partkey AS src, l_suppkey + {SUPPLIER_OFFSET} AS dst FROM lineitem",
    "d6": _pairs_sql("SELECT event_type, date_trunc('minute', ts) AS slot, user_id AS v FROM events", "event_type, slot"),
    "d7": _pairs_sql("SELECT event_type, date_trunc('hour', ts) AS slot, user_id AS v FROM events", "event_type, slot"),
    "d8": f"""WITH v AS (SELECT vec_id AS id, embedding::DOUBLE[] AS x FROM embeddings), c AS (
  SELECT a.id, b.id AS id2, round(list_cosine_similarity(a.x, b.x), 9) AS c FROM v a JOIN v b ON a.id <> b.id
), k AS (SELECT id, id2 FROM c QUALIFY row_number() OVER (PARTITION BY id ORDER BY c DESC, id2) <= {KNN})
SELECT DISTINCT least(id, id2) AS src, greatest(id, id2) AS dst FROM k""",
    "d9": f"""WITH l AS (SELECT DISTINCT doc_id AS v, trim(u.line, ' ') AS line FROM documents, unnest(string_split(text, chr(10))) AS u(line)), k AS (
  SELECT line FROM l WHERE length(line) >= {LINE_CHARS} GROUP BY line HAVING count(*) BETWEEN 2 AND {LINE_DOCS}
), r AS (SELECT v, line FROM l JOIN k USING (line)) SELECT DISTINCT a.v AS src, b.v AS dst FROM r a JOIN r b USING (line) WHERE a.v < b.v""",
    "d9_all": f"""WITH l AS (SELECT DISTINCT doc_id AS v, trim(u.line, ' ') AS line FROM documents, unnest(string_split(text, chr(10))) AS u(line))
SELECT DISTINCT a.v AS src, b.v AS dst FROM l a JOIN l b USING (line) WHERE a.v < b.v AND length(line) >= {LINE_CHARS}""",
    "d10": f"""WITH h AS (SELECT DISTINCT page_id, u.target FROM pages, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS u(target)), k AS (
  SELECT target, row_number() OVER (ORDER BY target) - 1 + {TARGET_OFFSET} AS id FROM (SELECT DISTINCT target FROM h)
) SELECT DISTINCT page_id AS src, id AS dst FROM h JOIN k USING (target)""",
    "d11": f"SELECT DISTINCT n_nationkey::BIGINT AS src, n_regionkey::BIGINT + {TARGET_OFFSET} AS dst FROM nation",
    "d12": f"""SELECT DISTINCT a.conv_id * {TURN_STEP} + a.turn AS src, a.conv_id * {TURN_STEP} + a.turn + 1 AS dst
FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1""",
    "d13": f"SELECT DISTINCT doc_id AS src, item_id + {TARGET_OFFSET} AS dst FROM documents d JOIN benchmark b ON contains(d.text, substr(b.text, 1, {LEAK_CHARS}))",
}
