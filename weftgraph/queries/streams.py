"""Streaming queries; each one's final state equals a batch answer, which is the oracle."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..sources.graphs import EDGES_SQL, graph
from ..sources.io import scratch
from ..streaming import events as st
from .engine import TRIANGLES, with_edges

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return add


def _events(spark, sf):
    return spark.read.parquet(f"{sf}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")


def _stream(spark, sf, **more):
    return st.replay(spark, _events(spark, sf), **more)


@query("st_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, sf):
    return st.finish(st.tumbling(_stream(spark, sf)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("st_sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 1 HOUR, ts), time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR]) AS start FROM events) t GROUP BY 1")
def _(spark, sf):
    return st.finish(st.sliding(_stream(spark, sf)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(
    "st_session",
    "WITH x AS (SELECT *, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), "
    "y AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM x) SELECT user_id, min(ts) AS start, count(*) AS n FROM y GROUP BY user_id, s",
)
def _(spark, sf):
    out = st.finish(st.sessions(_stream(spark, sf)), "complete")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("st_dedup_watermark", "SELECT event_id, user_id FROM events")
def _(spark, sf):
    e = _events(spark, sf)
    return st.finish(st.deduplicated(st.replay(spark, e.unionByName(e.where("event_id % 3 = 0")))), on_disk=True).select("event_id", "user_id")


_AGAIN = 1_000_000_000


@query(
    "st_late_rows",
    "SELECT count(*) AS kept, count(*) FILTER (WHERE event_id % 10 = 0 AND ts < (SELECT min(ts) + (max(ts) - min(ts)) / 3 FROM events)) AS late FROM events",
)
def _(spark, sf):
    """Rows of the first third of the time come once more, as new events, after all others: the watermark is beyond them, so they
    are dropped. kept: events that came in time and were let through; late: events that came late and were not."""
    e = _events(spark, sf)
    edge = e.agg((F.min("ts") + (F.max("ts") - F.min("ts")) / 3).alias("edge"), F.max("ts").alias("last"))
    again = e.crossJoin(edge).where("event_id % 10 = 0 and ts < edge")  # one row on that side
    rows = e.withColumn("at", F.col("ts")).unionByName(again.select((F.col("event_id") + _AGAIN).alias("event_id"), "ts", "user_id", "event_type", (F.col("last") + F.expr("interval 1 hour")).alias("at")))
    through = st.finish(st.deduplicated(st.replay(spark, rows, order="at", per_trigger=1).drop("at"), "1 minute"))
    came = through.agg(F.count_if(F.col("event_id") < _AGAIN).alias("kept"), F.count_if(F.col("event_id") >= _AGAIN).alias("got"))
    sent = again.agg(F.count(F.lit(1)).alias("sent"))
    return came.crossJoin(sent).select("kept", (F.col("sent") - F.col("got")).alias("late"))


@query("st_stream_static", "SELECT event_id, c_mktsegment AS segment FROM events JOIN customer ON c_custkey = user_id")
def _(spark, sf):
    customers = spark.read.parquet(f"{sf}/customer.parquet").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    return st.finish(st.with_customers(_stream(spark, sf), customers))


@query("st_stream_stream", "SELECT DISTINCT a.user_id AS u, b.user_id AS v FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id < b.user_id AND abs(date_diff('microsecond', a.ts, b.ts)) <= 60000000")
def _(spark, sf):
    return st.finish(st.coactive(_stream(spark, sf))).distinct()


def _changes(spark, sf, removed: bool):
    """d6's edges as a stream of additions, and the removal of every fifth one later."""
    e = graph(spark, sf, "d6").edges.select("src", "dst")
    rows = e.withColumns({"change": F.lit(1), "at": F.pmod(F.xxhash64("src", "dst"), F.lit(1000))})
    if removed:
        rows = rows.unionByName(e.where("(src + dst) % 5 = 0").withColumns({"change": F.lit(-1), "at": F.lit(2000).cast("long")}))
    return st.replay(spark, rows, order="at", files=4, per_trigger=1).drop("at")


@query("st_triangles", with_edges("d6", f"SELECT {TRIANGLES} AS n_triangles"))
def _(spark, sf):
    return spark.createDataFrame([(st.incremental_triangles(_changes(spark, sf, False)).total,)], "n_triangles long")


@query("st_triangles_removed", f"WITH e AS MATERIALIZED (SELECT * FROM ({EDGES_SQL['d6']}) t WHERE (src + dst) % 5 <> 0) SELECT {TRIANGLES} AS n_triangles")
def _(spark, sf):
    return spark.createDataFrame([(st.incremental_triangles(_changes(spark, sf, True)).total,)], "n_triangles long")


@query("st_degree_state", with_edges("d6", "SELECT id, deg FROM deg"))
def _(spark, sf):
    out = scratch(spark, "degrees")
    st.finish_batches(st.degree_state(_changes(spark, sf, False)), lambda b, k: b.withColumn("k", F.lit(k)).write.mode("append").parquet(out), "update")
    return spark.read.schema("id long, deg long, k int").parquet(out).groupBy("id").agg(F.max_by("deg", "k").alias("deg"))


@query("st_foreach_batch_upsert", "SELECT user_id, arg_max(event_id, {'t': ts, 'i': event_id}) AS event_id FROM events GROUP BY 1")
def _(spark, sf):
    sink = st.Upsert(spark, "user_id", "ts")
    st.finish_batches(_stream(spark, sf).select("user_id", "ts", "event_id"), sink)
    return sink.table().select("user_id", "event_id")


@query("st_restart", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf):
    """Stopped after the first half of the files, then started again from its checkpoint: no row is lost or doubled."""
    path, out, mark = scratch(spark, "stream"), scratch(spark, "out"), scratch(spark, "checkpoint")
    e = _events(spark, sf)

    def run():
        stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path)
        st.finish_batches(stream, lambda b, k: b.write.mode("overwrite").parquet(f"{out}/batch={k}"), checkpoint=mark)

    e.where("event_id % 2 = 0").repartition(2).write.mode("append").parquet(path)
    run()
    e.where("event_id % 2 = 1").repartition(2).write.mode("append").parquet(path)
    run()
    return spark.read.parquet(out).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
