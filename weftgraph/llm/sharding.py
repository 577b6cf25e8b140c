"""Contiguous shards of near equal bytes, from global prefix sums. DataFrame functions only.

Rows are put in one global order and cut into range partitions, which are written once. Each partition's total is
one row; a prefix sum over those few rows gives where each partition starts, and a window inside the partition does
the rest. A row belongs to the shard in whose equal share of all bytes its middle byte lies, so shards are
contiguous in the order and no shard is off its target by more than its two edge rows.

Order: id (null first), then the text's checksum, length and a 64-bit hash; rows equal in all of these are
interchangeable. Null text has no bytes and checksum 0. No rows give no rows. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, read


def byte_shards(df: DataFrame, shards: int, id_column: str = "doc_id", text: str = "text", overhead: int = 8) -> DataFrame:
    """``id_column``, size, text_crc32, shard (from 0), slot (gapless within the shard, from 0)."""
    data = F.encode(F.coalesce(F.col(text).cast("string"), F.lit("")), "UTF-8")
    rows = df.select(id_column, (F.length(data) + F.lit(overhead)).cast("long").alias("size"), F.crc32(data).alias("text_crc32"), F.xxhash64(data).alias("_h"))
    order = [F.col(id_column).asc_nulls_first(), "text_crc32", "size", "_h"]
    ranged = cut(rows.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()))
    # One row a partition: the number of partitions is the session's, not the data's.
    totals = ranged.groupBy("_part").agg(F.sum("size").alias("_bytes"), F.count(F.lit(1)).alias("_rows"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    starts = totals.select(
        "_part",
        F.coalesce(F.sum("_bytes").over(before), F.lit(0)).alias("_byte0"),
        F.coalesce(F.sum("_rows").over(before), F.lit(0)).alias("_row0"),
        F.sum("_bytes").over(whole).alias("_all"),
    )
    inside = Window.partitionBy("_part").orderBy(*order)
    middle = 2 * (F.col("_byte0") + F.col("_in")) - F.col("size")
    placed = (
        ranged.withColumn("_in", F.sum("size").over(inside.rowsBetween(Window.unboundedPreceding, 0)))
        .withColumn("_nth", F.row_number().over(inside))
        .join(F.broadcast(starts), "_part")
        .select(
            id_column, "size", "text_crc32", (F.col("_row0") + F.col("_nth") - 1).alias("_row"),
            F.least(F.lit(shards - 1), F.floor(middle.cast("decimal(38,0)") * shards / (2 * F.col("_all")).cast("decimal(38,0)"))).cast("int").alias("shard"),
        )
    )
    placed = cut(placed)
    firsts = placed.groupBy("shard").agg(F.min("_row").alias("_first"))  # one row a shard
    return placed.join(F.broadcast(firsts), "shard").select(id_column, "size", "text_crc32", "shard", (F.col("_row") - F.col("_first")).alias("slot"))


def op4_byte_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return byte_shards(docs, 24).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


#: The checksum's table is made from the polynomial of CRC-32, the rest from window sums.
OP4_SQL = """
WITH RECURSIVE steps(b, k, c) AS (
  SELECT b, 0, b FROM range(256) r(b)
  UNION ALL
  SELECT b, k + 1, CASE WHEN c % 2 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END FROM steps WHERE k < 8
), tab AS (SELECT list(c ORDER BY b) AS t FROM steps WHERE k = 8),
bytes AS (
  SELECT doc_id, octet_length(encode(coalesce(text, ''))) + 8 AS size,
    list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda x: ('0x' || x)::BIGINT) AS bs
  FROM documents
), sized AS (
  SELECT doc_id, size, xor(4294967295, list_reduce(list_concat([4294967295::BIGINT], bs),
    lambda acc, x: xor(acc >> 8, t[xor(acc & 255, x) + 1]))) AS text_crc32
  FROM bytes, tab
), sums AS (
  SELECT *, sum(size) OVER (ORDER BY doc_id NULLS FIRST, text_crc32, size ROWS UNBOUNDED PRECEDING) AS upto, sum(size) OVER () AS total FROM sized
), cutted AS (
  SELECT *, least(23, ((2 * upto - size)::HUGEINT * 24) // (2 * total)::HUGEINT)::INTEGER AS shard FROM sums
)
SELECT doc_id, size::BIGINT AS size, text_crc32::BIGINT AS text_crc32, 'bytes' AS law, shard,
  row_number() OVER (PARTITION BY shard ORDER BY doc_id NULLS FIRST, text_crc32, size) - 1 AS slot, NULL::INTEGER AS grown_shard
FROM cutted
"""
