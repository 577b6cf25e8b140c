"""Helpers shared by the corpus operators."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..shipping import ship

#: Rows of an Arrow batch are handled in slices of about this many text bytes.
SLICE_BYTES = 4 << 20

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the folder the cluster names. Where the session names none, a local one gets a folder of its own, any other an error."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        path = sc.getConf().get("spark.checkpoint.dir")
        if not path and not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(path or tempfile.mkdtemp(prefix="checkpoints-"))


def cut(df: DataFrame, task_bytes: int = 0) -> DataFrame:
    """Write ``df`` to the shared checkpoint folder and go on from the written rows.

    Shuffle files of the query that made the rows are given back at once: nothing reads them again. With ``task_bytes``
    neighbouring partitions are read back together until a task has about so much: a small table takes few tasks.
    """
    spark = df.sparkSession
    ensure_checkpoint_dir(spark)
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        out = df.select("*").checkpoint(eager=True)
    finally:
        spark.conf.set(_CLEANUP, before)
    gc.collect()
    return _together(out, task_bytes) if task_bytes else out


def _together(out: DataFrame, task_bytes: int) -> DataFrame:
    """The rows of a checkpoint in as many partitions as its files' bytes ask for, if it has more."""
    sc, rdd = out.sparkSession.sparkContext, out._jdf.queryExecution().analyzed().rdd()
    path = sc._jvm.org.apache.hadoop.fs.Path(rdd.getCheckpointFile().get())
    size = path.getFileSystem(sc._jsc.hadoopConfiguration()).getContentSummary(path).getLength()
    tasks = max(1, -(-size // task_bytes))
    return out.coalesce(tasks) if tasks < rdd.getNumPartitions() else out


def arrow_map(df: DataFrame, run: Callable, schema: str | T.StructType) -> DataFrame:
    """mapInArrow, with this package sent along."""
    ship(df.sparkSession)
    return df.mapInArrow(run, schema)


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", size: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches into slices of about ``size`` bytes of text; one long row is a slice of its own."""
    for batch in batches:
        sizes = np.asarray(pa.compute.fill_null(pa.compute.binary_length(batch.column(column)), 0), dtype=np.int64)
        if not len(sizes):
            continue
        ends = np.cumsum(sizes + 64)
        start = 0
        while start < len(sizes):
            base = ends[start - 1] if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, base + size, side="right")))
            yield batch.slice(start, stop - start)
            start = stop


class WordHashes(dict):
    """word -> 64-bit hash; starts anew when it holds ``limit`` words."""

    def __init__(self, limit: int = 400_000):
        super().__init__()
        self.limit = limit

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.limit:
            self.clear()
        made = self[word] = xxhash.xxh64_intdigest(word)
        return made

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def text_blobs(batch: pa.RecordBatch, column: str = "text") -> list[bytes]:
    """The UTF-8 bytes of a string column; null gives b''."""
    return [x or b"" for x in batch.column(column).cast(pa.binary()).to_pylist()]


def with_fields(df: DataFrame, keep: tuple[str, ...], extra: str) -> T.StructType:
    """Schema of the ``keep`` columns of ``df`` and then the columns of the DDL string ``extra``."""
    return T.StructType([df.schema[k] for k in keep] + T.StructType.fromDDL(extra).fields)


def stored(df: DataFrame) -> DataFrame:
    """Write whole documents as a Parquet table in the shared folder and read it again."""
    ensure_checkpoint_dir(df.sparkSession)
    path = f"{df.sparkSession.sparkContext.getCheckpointDir()}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def crc_mod(column: str, n: int) -> Column:
    """crc32 of an integer id written as decimal text, modulo n; null ids count as the empty string."""
    return F.pmod(F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")), F.lit(n))


def crc32(data: bytes) -> int:
    return zlib.crc32(data) & 0xFFFFFFFF


def mix64(x: np.ndarray) -> np.ndarray:
    """Finalizer of a 64-bit hash: every input bit moves every output bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")
