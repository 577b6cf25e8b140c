"""SimHash near-duplicates through a byte-position inverted index with count filtering.

A 64-bit fingerprint is eight bytes. Two fingerprints that differ in k bits share at least 8 - k positional bytes.
A list for each single byte would hold 1/256 of all rows, so a list holds the fingerprints that agree on four positions,
and the fourfold positions are chosen so that lists can be counted instead of bytes: of the 70 there are, those 14
whose numbers have the exclusive or zero. Every three positions lie in exactly one of them, whence two fingerprints
that share 8, 7, 6, 5 or fewer bytes meet in 14, 7, 3, 1 or at most one list. So the lists that a pair shares are
tallied, and pairs below the count that ``bits`` guarantees (3 lists, that is 6 bytes, for 2 bits) are dropped before
their bits are compared.

Equal fingerprints are one posting, so groups of exact copies cost one row. A list longer than ``list_limit`` is not paired
and counted but split: its members agree on four bytes and must agree on two more, so each is posted under the six choices
of these. Such a list is what the count asks for, and has 65,536 different fingerprints at most, two bytes being free. Where
it still is longer than ``list_limit``, its fingerprints post every value within one bit, and those under one value are linked
as a star: two fingerprints within two bits always share such a value and two that share one are within two bits. All of this is exact.

Null and blank texts have fingerprint zero, which links like any other; rows with equal ids are one node; a null id
takes no part in choosing a component's smallest id.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, cut, read, slices, text_blobs, with_fields
from .graphs import components

SHINGLES_AT_ONCE = 1 << 20


def fingerprint(data: bytes, words: int = 3, seed: int = 42) -> int:
    """The 64-bit SimHash of a text's word shingles, repeats included; A-Z are lower-cased, white space is ASCII."""
    own = data.lower().split()
    if not own:
        return 0
    joined, n = b" ".join(own), max(1, len(own) - words + 1)
    ends = np.cumsum(np.fromiter(map(len, own), np.int64, len(own)) + 1)
    starts = np.concatenate(([0], ends[: n - 1])).tolist()
    stops = (ends[words - 1 :] - 1).tolist() if len(own) >= words else [len(joined)]
    digest, counts = xxhash.xxh64_intdigest, np.zeros(64, np.int64)
    for at in range(0, n, SHINGLES_AT_ONCE):
        hashes = np.array([digest(joined[i:j], seed) for i, j in zip(starts[at : at + SHINGLES_AT_ONCE], stops[at : at + SHINGLES_AT_ONCE], strict=True)], np.uint64)
        for k in range(0, len(hashes), 1 << 14):
            counts += np.unpackbits(hashes[k : k + (1 << 14)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * counts > n, bitorder="little").view("<u8")[0])


def fingerprints(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), words: int = 3) -> DataFrame:
    """``keep`` columns and ``fp``, the fingerprint as a signed long."""
    schema = with_fields(df, keep, "fp long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text):
            fps = np.array([fingerprint(b, words) for b in text_blobs(batch, text)], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keep), pa.array(fps)], [*keep, "fp"])

    return arrow_map(df.select(*keep, text), run, schema)


#: Fourfold byte positions of which every three positions lie in exactly one.
FOURS = [c for c in combinations(range(8), 4) if c[0] ^ c[1] ^ c[2] ^ c[3] == 0]


def guaranteed(bits: int) -> int:
    """Lists that any two fingerprints within ``bits`` bits share."""
    return min(sum(not {*gone} & {*four} for four in FOURS) for gone in combinations(range(8), bits))


def _mask(positions) -> int:
    mask = sum(0xFF << (8 * p) for p in positions)
    return mask - (1 << 64) if mask >> 63 else mask


def _postings() -> Column:
    """For each four positions: which, and a key of the bytes they hold."""
    keys = [F.struct(F.lit(k).alias("four"), F.xxhash64(F.lit(k), F.col("fp").bitwiseAND(F.lit(_mask(four)))).alias("posting")) for k, four in enumerate(FOURS)]
    return F.inline(F.array(*keys))


def _splits(bits: int) -> Column:
    """For a member of a list, a key for each choice of further positions in which it must agree with one within ``bits`` bits."""
    rest = [[_mask(c) for c in combinations(sorted({*range(8)} - {*four}), 4 - bits)] for four in FOURS]
    masks = F.element_at(F.array(*(F.array(*map(F.lit, own)) for own in rest)), F.col("four") + 1)
    return F.explode(F.transform(masks, lambda m: F.xxhash64(F.col("posting"), m, F.col("fp").bitwiseAND(m)))).alias("posting")


def _lists(posted: DataFrame, list_limit: int) -> tuple[DataFrame, DataFrame]:
    """Pairs (a, b) of each short list, one row a list they share, and the members of the long ones."""
    sizes = cut(posted.groupBy("posting").agg(F.count(F.lit(1)).alias("n"), F.min("fp").alias("a"), F.max("fp").alias("b")).where("n > 1"))
    members = posted.join(sizes.where("n > 2").select("posting", "n"), "posting")
    lists = members.where(F.col("n") <= list_limit).groupBy("posting").agg(F.collect_list("fp").alias("fps"))
    listed = lists.select("fps", F.explode("fps").alias("a")).select("a", F.explode("fps").alias("b")).where("a < b")
    return sizes.where("n = 2").select("a", "b").unionByName(listed), members.where(F.col("n") > F.greatest(F.lit(list_limit), F.lit(2))).drop("n")


def tally(pairs: DataFrame, least: int) -> DataFrame:
    """Distinct pairs that share ``least`` lists or more, and how many."""
    return pairs.groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared")).where(F.col("shared") >= least)


def links(fps: DataFrame, bits: int = 2, list_limit: int = 64) -> DataFrame:
    """Links (a, b) among distinct fingerprints ``fp`` that connect all those within ``bits`` bits, two at most."""
    if not 0 <= bits <= 2:
        raise ValueError("bits must be 0, 1 or 2")
    pairs, long = _lists(fps.select("fp", _postings()), list_limit)
    long = cut(long)
    split, dense = _lists(long.select("fp", _splits(bits)), list_limit)
    near = F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= bits
    found = tally(pairs, guaranteed(bits)).where(near).select("a", "b").unionByName(tally(split, 1).where(near).select("a", "b"))
    masks = [0, *((1 << b) - (1 << 64) if b == 63 else 1 << b for b in range(64))]
    dense = dense.select("fp").distinct()
    if bits == 2:
        spread = dense.select("fp", F.explode(F.array(*(F.col("fp").bitwiseXOR(F.lit(m)) for m in masks))).alias("value"))
        stars = spread.join(spread.groupBy("value").agg(F.min("fp").alias("a"), F.count(F.lit(1)).alias("n")).where("n > 1").select("value", "a"), "value")
        stars = stars.where("a < fp").select("a", F.col("fp").alias("b"))
    else:  # within one bit: look each neighbour up
        spread = dense.select(F.col("fp").alias("a"), F.explode(F.array(*(F.col("fp").bitwiseXOR(F.lit(m)) for m in masks[1:] if bits))).alias("fp"))
        stars = spread.join(dense, "fp").select("a", F.col("fp").alias("b"))
    return found.unionByName(stars).distinct()


def near_duplicates(df: DataFrame, id_column: str = "doc_id", text: str = "text", bits: int = 2, list_limit: int = 64, words: int = 3) -> DataFrame:
    """``id_column``, ``fp`` and ``component_id``, the smallest id among all rows reachable through links."""
    own = cut(fingerprints(df, text, (id_column,), words))
    distinct = cut(own.groupBy("fp").agg(F.min(id_column).alias("least")))
    found = components(links(distinct, bits, list_limit))
    named = distinct.join(found.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("component", "fp").alias("component"))
    roots = named.groupBy("component").agg(F.min("least").alias("component_id"))
    named = named.join(roots, "component").select("fp", "component_id")
    return own.join(named, "fp", "left").select(id_column, "fp", "component_id")


def op2_simhash_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return near_duplicates(docs).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
