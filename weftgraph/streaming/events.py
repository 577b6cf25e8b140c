"""Structured Streaming over event files: windows, deduplication, joins, and state that counts triangles and degrees.

Each function takes a streaming DataFrame with event_id, ts, user_id, event_type; ``replay`` makes one from a table
and ``finish`` runs a query to its end and returns what it left.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager, nullcontext

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..shipping import ship
from ..sources.io import scratch

PER_TRIGGER = 2

_STORE = "spark.sql.streaming.stateStore"
STATE = {
    f"{_STORE}.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    f"{_STORE}.rocksdb.boundedMemoryUsage": "true", f"{_STORE}.rocksdb.maxMemoryUsageMB": "256",
}


def replay(spark: SparkSession, table: DataFrame, order: str = "ts", files: int = 6, per_trigger: int = PER_TRIGGER) -> DataFrame:
    """A file stream of the table, cut into files by ``order`` and written one after another, so that the stream,
    which goes by the files' times, reads them in that order; some files a trigger."""
    path = scratch(spark, "stream")
    ranged = table.repartitionByRange(files, order).withColumn("_file", F.spark_partition_id()).persist()
    for k in range(files):
        ranged.where(F.col("_file") == k).drop("_file").coalesce(1).write.mode("append").parquet(path)
    ranged.unpersist()
    return spark.readStream.schema(table.schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def finish(df: DataFrame, mode: str = "append", checkpoint: str | None = None, on_disk: bool = False) -> DataFrame:
    """Run over all input there is, and return what the sink holds then (complete or append mode).

    The sink is a folder of files: each batch writes its own, in complete mode the last one counts. Nothing is gathered on the driver.
    on_disk: keep the state in RocksDB.
    """
    spark = df.sparkSession
    out = scratch(spark, "sink")
    numbers: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")
        numbers.append(number)

    finish_batches(df, keep, mode, checkpoint, on_disk)
    held = numbers[-1:] if mode == "complete" else numbers
    return spark.read.schema(df.schema).parquet(*(f"{out}/batch={k}" for k in held)) if held else spark.createDataFrame([], df.schema)


def finish_batches(df: DataFrame, each: Callable[[DataFrame, int], None], mode: str = "append", checkpoint: str | None = None, on_disk: bool = False) -> None:
    """Run over all input there is with a function per micro-batch."""
    with _state_on_disk(df.sparkSession) if on_disk else nullcontext():
        query = df.writeStream.foreachBatch(each).outputMode(mode).option("checkpointLocation", checkpoint or scratch(df.sparkSession, "checkpoint")).trigger(availableNow=True).start()
        try:
            query.awaitTermination()
        finally:
            query.stop()


@contextmanager
def _state_on_disk(spark: SparkSession) -> Iterator[None]:
    """State in RocksDB, whose memory is bounded, for queries started inside; the default store holds all state in the heap."""
    before = {k: spark.conf.get(k, None) for k in STATE}
    for k, v in STATE.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


def tumbling(events: DataFrame, width: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Events per type and window."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 hours", slide: str = "1 hour", late: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, slide).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    """A user's bursts of events."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(events: DataFrame, late: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join: each event with its customer's segment."""
    return events.join(customers, "user_id").select("event_id", "segment")


def coactive(events: DataFrame, seconds: int = 60, late: str = "1 day") -> DataFrame:
    """Stream-stream join: users with an event of the same type at most ``seconds`` apart, u < v."""
    a = events.select(F.col("event_type").alias("k1"), F.col("user_id").alias("u"), F.col("ts").alias("t1")).withWatermark("t1", late)
    b = events.select(F.col("event_type").alias("k2"), F.col("user_id").alias("v"), F.col("ts").alias("t2")).withWatermark("t2", late)
    near = F.expr(f"k1 = k2 and u < v and t2 >= t1 - interval {seconds} seconds and t2 <= t1 + interval {seconds} seconds")
    return a.join(b, near).select("u", "v")


def degree_state(edges: DataFrame) -> DataFrame:
    """id, deg after every batch of edge changes (src, dst, change +1 or -1): state per vertex.

    The state is the neighbour multiset, so repeated edges count once and deletions undo them.
    """
    ship(edges.sparkSession)
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.col("dst").alias("nbr"), "change"), F.struct(F.col("dst").alias("id"), F.col("src").alias("nbr"), "change"))).alias("x")).select("x.*")

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ids, times = state.get if state.exists else ([], [])
        held = dict(zip(ids, times, strict=True))
        for b in batches:
            for nbr, change in zip(b["nbr"].tolist(), b["change"].tolist(), strict=True):
                held[nbr] = held.get(nbr, 0) + change
        held = {k: n for k, n in held.items() if n}
        state.update((list(held), list(held.values())))
        yield pd.DataFrame({"id": [key[0]], "deg": [sum(n > 0 for n in held.values())]})

    return ends.groupBy("id").applyInPandasWithState(update, "id long, deg long", "ids array<long>, times array<long>", "update", GroupStateTimeout.NoTimeout)


class TriangleCounter:
    """Triangle count of a growing and shrinking graph, kept up batch by batch.

    The state is a log: each batch adds a folder of the edges that came and went, under the batch's number, and its total.
    Nothing written before is written again, and a repeated or restarted batch starts from the last total before
    it. Triangles gained are those of the new graph with at least one new edge, counted by how many of their edges
    are new; triangles lost likewise on the old graph with removed edges. Only edges at a changed edge's ends are joined.
    """

    LOG, TOTAL = "src long, dst long, sign int, batch int", "n long, batch int"

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path = spark, path or scratch(spark, "triangles")
        self._write(spark.createDataFrame([], "src long, dst long, sign int"), "log", -1, "ignore")
        self._write(spark.createDataFrame([(0,)], "n long"), "total", -1, "ignore")

    def _write(self, rows: DataFrame, kind: str, batch: int, mode: str = "overwrite") -> None:
        rows.write.mode(mode).parquet(f"{self.path}/{kind}/batch={batch}")

    def edges(self, batch: int) -> DataFrame:
        """The edges there are after a batch."""
        log = self.spark.read.schema(self.LOG).parquet(f"{self.path}/log").where(F.col("batch") <= batch)
        return log.groupBy("src", "dst").agg(F.sum("sign").alias("c")).where("c > 0").select("src", "dst")

    @property
    def done(self) -> dict[int, int]:
        """The total after each batch; as many rows as batches."""
        return {r["batch"]: r["n"] for r in self.spark.read.schema(self.TOTAL).parquet(f"{self.path}/total").collect()}

    @staticmethod
    def touching(edges: DataFrame, part: DataFrame) -> int:
        """Triangles of ``edges`` with an edge in ``part``, a subset of them."""
        ends = part.select(F.explode(F.array("src", "dst")).alias("a")).distinct()
        marked = edges.join(part.withColumn("new", F.lit(1)), ["src", "dst"], "left").select("src", "dst", F.coalesce("new", F.lit(0)).alias("new"))
        both = marked.select(F.col("src").alias("a"), F.col("dst").alias("c"), "new").unionByName(marked.select(F.col("dst").alias("a"), F.col("src").alias("c"), "new")).join(ends, "a", "left_semi")
        x = part.select(F.col("src").alias("a"), F.col("dst").alias("b"))
        y, z = both.withColumnRenamed("new", "n1"), both.select(F.col("a").alias("b"), "c", F.col("new").alias("n2"))
        found = x.join(y, "a").join(z, ["b", "c"]).groupBy((F.col("n1") + F.col("n2") + 1).alias("k")).agg(F.count(F.lit(1)).alias("n")).collect()  # three rows
        return sum(r["n"] // r["k"] for r in found)

    def __call__(self, batch: DataFrame, number: int) -> None:
        before = {k: n for k, n in self.done.items() if k < number}
        last = max(before)
        old = self.edges(last)
        changes = batch.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "change").where("src <> dst").groupBy("src", "dst").agg(F.sum("change").alias("c"))
        more = changes.where("c > 0").select("src", "dst").join(old, ["src", "dst"], "left_anti").withColumn("sign", F.lit(1))
        less = changes.where("c < 0").select("src", "dst").join(old, ["src", "dst"], "left_semi").withColumn("sign", F.lit(-1))
        self._write(more.unionByName(less), "log", number)
        own = self.spark.read.schema("src long, dst long, sign int").parquet(f"{self.path}/log/batch={number}")
        gained = self.touching(self.edges(number), own.where("sign = 1").select("src", "dst"))
        lost = self.touching(old, own.where("sign = -1").select("src", "dst"))
        self._write(self.spark.createDataFrame([(before[last] + gained - lost,)], "n long"), "total", number)

    @property
    def total(self) -> int:
        found = self.done
        return found[max(found)]


def incremental_triangles(edge_changes: DataFrame, checkpoint: str | None = None, path: str | None = None) -> TriangleCounter:
    """Run the counter over a stream of src, dst, change; with the same ``checkpoint`` and ``path`` it goes on where it was."""
    counter = TriangleCounter(edge_changes.sparkSession, path)
    finish_batches(edge_changes, counter, checkpoint=checkpoint)
    return counter


class Upsert:
    """Idempotent sink: per batch the latest row of each key, over what the batches before left."""

    def __init__(self, spark: SparkSession, key: str, at: str, path: str | None = None):
        self.spark, self.key, self.at, self.path = spark, key, at, path or scratch(spark, "upsert")
        self.last = -1

    def __call__(self, batch: DataFrame, number: int) -> None:
        rows = batch
        if number > 0:
            rows = rows.unionByName(self.spark.read.parquet(f"{self.path}/{number - 1}"))
        names = [c for c in rows.columns if c != self.key]
        best = rows.groupBy(self.key).agg(F.max_by(F.struct(*names), F.struct(self.at, *names)).alias("r")).select(self.key, "r.*")
        best.write.mode("overwrite").parquet(f"{self.path}/{number}")
        self.last = number

    def table(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/{self.last}")
