"""Near copies: SimHash near-duplicates with five-word shingles, completed and decided by whole-text Jaccard similarity.

A text is the set of its word shingles. Pairs are proposed by the positional-byte index over SimHash fingerprints of the
shingles, and, since that index reaches two bits and a pair at similarity 0.8 differs in ten of 64 bits on the mean, by bands of a
MinHash signature too: two texts are compared if a band agrees. A pair at similarity s meets in no band with
probability (1 - s ** ROWS) ** BANDS: 5e-7 at 0.8, less above. Each proposed pair is compared on both whole sets, so no pair
below the threshold is linked.

Texts with equal sets are one node. In a list of nodes that agree in a band each is compared with one of the list only,
again after each round with one of another component: what is compared grows with the nodes. Members of one component need
no further link. A node left in a list with another component can be similar to one of them only if at least that share of its
shingles stands in some other node that is left, so nodes with too many shingles of their own drop out, which is what
copies with changes of their own are.

The rest is not compared list by list. Nodes that lists connect form a group, and a group has a centre: the shingles that over
half of it hold. Let d be the shingles in which a node differs from the centre, n the node's own number, and its weight
w = (100 + percent) * |d| - (100 - percent) * n. Two nodes are similar if and only if 2 * (100 + percent) times the number of
differences that they share is at least the sum of their weights. Where that sum is not above zero they are similar, and both
are to the node of least weight: one star links all of these. All others share differences, and so many that they meet under
one of the first (rarest first) that do not leave too few behind. There again each is compared with the list's node of
least weight before it is with others. What copies of one template have in common is in no list. Nothing is lost by any of this.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common, graphs
from .common import WordHashes, arrow_map, mix64, slices, text_blobs, with_fields
from .simhash import links

WORDS, BANDS, ROWS, STAR_ROUNDS = 5, 48, 6, 3
#: Nodes of a group that meet one copy of its centre.
GROUP_ROWS = 200
#: Bytes of a written table that one task reads back. Most tables here are small and there are many steps.
TASK_BYTES = 128 << 10
#: Odd multipliers and masks of the signature's hash functions, and the multipliers of a shingle's words.
_RANDOM = np.random.default_rng(42).integers(0, 1 << 64, (3, BANDS * ROWS), np.uint64)
_TIMES, _MASKS, _PLACES = _RANDOM[0] | np.uint64(1), _RANDOM[1], _RANDOM[2] | np.uint64(1)

cut = partial(common.cut, task_bytes=TASK_BYTES)
components = partial(graphs.components, gathered=graphs.GATHERED)


def shingles(data: bytes, hashes: WordHashes, words: int = WORDS) -> np.ndarray:
    """Hashes of the word shingles, repeats included; A-Z are lower-cased, white space is ASCII, a shorter text is one shingle."""
    own = hashes.of(data.lower().split())
    n = len(own) - words + 1
    if n < 1:
        return mix64((own * _PLACES[: len(own)]).sum(dtype=np.uint64, keepdims=True) + np.uint64(len(own))) if len(own) else own
    total = np.full(n, words, np.uint64)
    for k in range(words):
        total += own[k : k + n] * _PLACES[k]
    return mix64(total)


def _simhash(all_hashes: np.ndarray) -> int:
    """Each bit is 1 if set in over half the hashes."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(all_hashes), 1 << 14):
        ones += np.unpackbits(all_hashes[at : at + (1 << 14)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(all_hashes), bitorder="little").view("<u8")[0])


def _bands(sets: list[np.ndarray]) -> np.ndarray:
    """A row of band keys for each set; no set may be empty."""
    joined, starts = np.concatenate(sets), np.cumsum([0, *map(len, sets[:-1])])
    keys = np.zeros((len(sets), BANDS), np.uint64)
    for i in range(BANDS * ROWS):
        least = np.minimum.reduceat((joined ^ _MASKS[i]) * _TIMES[i], starts)
        keys[:, i // ROWS] = mix64(keys[:, i // ROWS] * _PLACES[0] + least + np.uint64(i))
    return keys


def _key(own: np.ndarray) -> int:
    return int(mix64(own ^ _MASKS[0]).sum(dtype=np.uint64))


def signatures(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), words: int = WORDS) -> DataFrame:
    """``keep`` columns, ``key`` of the shingle set, its size ``n``, its SimHash ``fp``, and ``bands``, which an empty set has none of."""
    schema = with_fields(df, keep, "key long, n long, fp long, bands array<long>")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in slices(batches, text):
            sets, fps = [], []
            for data in text_blobs(batch, text):
                every = shingles(data, hashes, words)
                fps.append(_simhash(every))
                sets.append(np.unique(every))
            full = [s for s in sets if len(s)]
            keys = np.array([_key(s) for s in sets], np.uint64).view(np.int64)
            flat = _bands(full).view(np.int64).ravel() if full else np.zeros(0, np.int64)
            ends = np.cumsum([0, *(BANDS * bool(len(s)) for s in sets)]).astype(np.int32)
            bands = pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keep), pa.array(keys), pa.array([len(s) for s in sets], pa.int64()), pa.array(np.array(fps, np.uint64).view(np.int64)), bands], [*keep, "key", "n", "fp", "bands"])

    return arrow_map(df.select(*keep, text), run, schema)


def _sets(df: DataFrame, text: str, words: int) -> DataFrame:
    """``key`` and ``shingles`` of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in slices(batches, text):
            sets = [np.unique(shingles(b, hashes, words)) for b in text_blobs(batch, text)]
            keys = np.array([_key(s) for s in sets], np.uint64).view(np.int64)
            ends = np.cumsum([0, *map(len, sets)]).astype(np.int32)
            flat = np.concatenate([np.zeros(0, np.uint64), *sets]).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], ["key", "shingles"])

    return arrow_map(df.select(text), run, "key long, shingles array<long>")


def _similar(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets' Jaccard similarity is ``percent`` hundredths or more, in whole numbers."""
    both = pairs.join(sets.toDF("b", "y"), "b").join(sets.toDF("a", "x"), "a")
    shared, total = F.size(F.array_intersect("x", "y")).cast("long"), (F.size("x") + F.size("y")).cast("long")
    return both.where(shared * (100 + percent) >= total * percent).select("a", "b")


def _proposed(nodes: DataFrame) -> DataFrame:
    """Pairs (a, b) of keys whose fingerprints are equal or linked; one key stands for all of a fingerprint in the links."""
    named = cut(nodes.where("n > 0").groupBy("fp").agg(F.min("key").alias("lead"), F.count(F.lit(1)).alias("keys")))
    equal = nodes.join(named.where("keys > 1"), "fp").where("key > lead").select(F.col("lead").alias("a"), F.col("key").alias("b"))
    near = links(named.select("fp"))
    near = near.join(named.select(F.col("fp").alias("a"), F.col("lead").alias("x")), "a").join(named.select(F.col("fp").alias("b"), F.col("lead").alias("y")), "b")
    return equal.unionByName(near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")))


def _near_size(a: str, b: str, percent: int) -> Column:
    return (F.col(a) * 100 >= F.col(b) * percent) & (F.col(b) * 100 >= F.col(a) * percent)


def _mixed(members: DataFrame) -> DataFrame:
    """The lists that hold two components or more: posting, lead (the member with the smallest component)."""
    lists = members.groupBy("posting").agg(F.min(F.struct("component", "key", "n")).alias("lead"), F.max("component").alias("most"))
    return lists.where("lead.component < most").select("posting", "lead")


def _stars(members: DataFrame, tested: DataFrame | None, percent: int) -> DataFrame:
    """For each member one pair with the leader of a list whose component is another."""
    found = members.join(_mixed(members), "posting").where("component != lead.component")
    found = found.select(F.col("lead.key").alias("a"), F.col("key").alias("b"), F.col("lead.n").alias("na"), F.col("n").alias("nb")).where(_near_size("na", "nb", percent)).select("a", "b")
    if tested is not None:
        found = found.distinct().join(tested, ["a", "b"], "left_anti")
    return found.groupBy("b").agg(F.min("a").alias("a")).select("a", "b")


def _rest(members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Members of lists with several components, and ``common``, how many of their shingles some other of them has; without
    those that have too few of these."""
    left = cut(members.join(_mixed(members).select("posting"), "posting", "left_semi"))
    keys = left.select("key").distinct()
    every = sets.join(keys, "key", "left_semi").select("key", F.explode("shingles").alias("shingle"))
    alone = every.groupBy("shingle").agg(F.min("key").alias("key"), F.count(F.lit(1)).alias("held")).where("held = 1").groupBy("key").agg(F.count(F.lit(1)).alias("own"))
    able = left.join(alone, "key", "left").withColumn("common", F.col("n") - F.coalesce("own", F.lit(0)))
    return cut(able.where(F.col("common") * 100 >= F.col("n") * percent).drop("own"))


def _differences(rest: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """key, component, grp, w, d: the nodes in lists with others, their group, weight, and differences from the group's centre."""
    first = rest.groupBy("posting").agg(F.min("key").alias("first"))
    grouped = components(rest.join(first, "posting"), "first", "key").toDF("key", "grp").join(rest.select("key", "component").distinct(), "key")
    own = cut(sets.join(grouped, "key"))
    sizes = own.groupBy("grp").agg(F.count(F.lit(1)).alias("size"), F.ceil(F.count(F.lit(1)) / GROUP_ROWS).alias("salts"))
    held = own.select("grp", F.explode("shingles").alias("shingle")).groupBy("grp", "shingle").agg(F.count(F.lit(1)).alias("held"))
    centres = held.join(F.broadcast(sizes), "grp").where(F.col("held") * 2 > F.col("size")).groupBy("grp", "salts").agg(F.collect_list("shingle").alias("centre"))
    centres = centres.select("grp", F.explode(F.sequence(F.lit(0).cast("long"), F.col("salts") - 1)).alias("salt"), "centre")
    salted = own.join(F.broadcast(sizes), "grp").withColumn("salt", F.pmod(F.xxhash64("key"), "salts"))
    centre = F.coalesce("centre", F.array().cast("array<long>"))
    both = salted.join(centres, ["grp", "salt"], "left").withColumn("d", F.concat(F.array_except("shingles", centre), F.array_except(centre, "shingles")))
    return cut(both.select("key", "component", "grp", (F.size("d").cast("long") * (100 + percent) - F.size("shingles").cast("long") * (100 - percent)).alias("w"), "d"))


def _merged(nodes: DataFrame, found: DataFrame) -> DataFrame:
    """The nodes with the components that the links ``found`` make of theirs."""
    ends = [nodes.select(F.col("key").alias(k), F.col("component").alias(f"c{k}")) for k in "ab"]
    joined = components(found.join(ends[0], "a").join(ends[1], "b"), "ca", "cb").toDF("component", "whole")
    return cut(nodes.join(joined, "component", "left").withColumn("component", F.coalesce("whole", "component")).select(*nodes.columns))


def _open(nodes: DataFrame, percent: int) -> DataFrame:
    """The nodes that may be similar to one of another component: ``d`` is what they share with other components, rarest first,
    ``c`` how much that is, and ``ask`` how many of its first each is to be listed under."""
    least = nodes.groupBy("grp", "component").agg(F.min("w").alias("w"))
    lead = least.groupBy("grp").agg(F.min(F.struct("w", "component")).alias("lead"))
    other = least.join(F.broadcast(lead), "grp").groupBy("grp", "lead").agg(F.min(F.when(F.col("component") != F.col("lead.component"), F.col("w"))).alias("second")).where("second is not null")
    each = nodes.select("grp", "key", "component", "w", F.explode("d").alias("x"))
    shared = each.groupBy("grp", "x").agg(F.count(F.lit(1)).alias("held"), F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi").select("grp", "x", "held")
    listed = each.join(shared, ["grp", "x"]).groupBy("grp", "key", "component", "w").agg(F.sort_array(F.collect_list(F.struct("held", "x"))).alias("d"))
    best = F.when(F.col("component") == F.col("lead.component"), F.col("second")).otherwise(F.col("lead.w"))
    asked = listed.join(F.broadcast(other), "grp").withColumn("c", F.size("d")).withColumn("least", F.greatest(F.lit(1), F.ceil((F.col("w") + best) / F.lit(2 * (100 + percent)))))
    return cut(asked.where("least <= c").select("key", "component", "grp", "w", F.col("d.x").alias("d"), "c", (F.col("c") - F.col("least") + 1).cast("int").alias("ask")))


def _alike(pairs: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """The pairs that share as many differences as their weights ask."""
    both = pairs.join(nodes.select(F.col("key").alias("a"), F.col("w").alias("wa"), F.col("d").alias("da")), "a").join(nodes.select(F.col("key").alias("b"), F.col("w").alias("wb"), F.col("d").alias("db")), "b")
    return cut(both.where(F.size(F.array_intersect("da", "db")) * 2 * (100 + percent) >= F.col("wa") + F.col("wb")).select("a", "b"))


def _links_of_rest(rest: DataFrame, sets: DataFrame, percent: int, rounds: int = STAR_ROUNDS) -> DataFrame:
    """Links (a, b) that connect what similar nodes of different components in ``rest`` connect."""
    nodes = _differences(rest, sets, percent)
    lead = nodes.groupBy("grp").agg(F.min(F.struct("w", "key", "component")).alias("lead"))
    sure = nodes.join(F.broadcast(lead), "grp").where((F.col("key") != F.col("lead.key")) & (F.col("component") != F.col("lead.component")) & (F.col("w") + F.col("lead.w") <= 0))
    found = cut(sure.select(F.col("lead.key").alias("a"), F.col("key").alias("b")))
    nodes = _open(_merged(nodes, found), percent)

    def under() -> DataFrame:
        return nodes.select("grp", "key", "component", "w", "c", F.posexplode(F.slice("d", F.lit(1), F.col("ask"))).alias("at", "x"))

    def able(a: str, b: str) -> Column:
        left = F.least(F.col(f"{a}c") - F.col(f"{a}at"), F.col(f"{b}c") - F.col(f"{b}at"))  # if this is the first difference they share
        return (F.col(f"{a}component") != F.col(f"{b}component")) & (left * 2 * (100 + percent) >= F.col(f"{a}w") + F.col(f"{b}w"))

    for _ in range(rounds):
        if nodes.isEmpty():
            return found
        posts = under()
        led = posts.groupBy("grp", "x").agg(F.min(F.struct("w", "component", "key", "c", "at")).alias("lead"))
        asks = posts.join(led, ["grp", "x"]).where(able("lead.", "")).select(F.col("lead.key").alias("a"), F.col("key").alias("b")).distinct()
        more = _alike(asks, nodes, percent)
        if more.isEmpty():
            break
        found = found.unionByName(more)
        nodes = _open(_merged(nodes.select("key", "component", "grp", "w", "d"), more), percent)
    a, b = (under().select("grp", "x", *(F.col(c).alias(k + c) for c in ("key", "component", "w", "c", "at"))) for k in "ab")
    pairs = a.join(b, ["grp", "x"]).where((F.col("akey") < F.col("bkey")) & able("a", "b")).select(F.col("akey").alias("a"), F.col("bkey").alias("b")).distinct()
    return found.unionByName(_alike(pairs, nodes, percent))


def near_copies(df: DataFrame, id_column: str = "doc_id", text: str = "text", percent: int = 80, words: int = WORDS, rounds: int = STAR_ROUNDS) -> DataFrame:
    """``id_column`` and ``component_id``, the smallest id among all rows that near copies lead to.

    Null and blank texts have no shingles and are copies of each other.
    """
    own = cut(signatures(df, text, (id_column,), words))
    nodes = cut(own.groupBy("key").agg(F.min(id_column).alias("least"), F.min("n").alias("n"), F.min("fp").alias("fp"), F.any_value("bands").alias("bands")))
    posted = nodes.select("key", "n", F.explode("bands").alias("posting"))
    sizes = posted.groupBy("posting").agg(F.count(F.lit(1)).alias("listed")).where("listed > 1").select("posting")
    members = cut(posted.join(sizes, "posting"))
    proposed = cut(_proposed(nodes))
    asked = cut(members.select("key").unionByName(proposed.select(F.explode(F.array("a", "b")).alias("key"))).distinct())
    ids = nodes.join(asked, "key", "left_semi").select(F.col("least").alias(id_column)).distinct()
    sets = cut(_sets(df.join(ids, id_column, "left_semi"), text, words).join(asked, "key", "left_semi").dropDuplicates(["key"]))

    def told(labels: DataFrame) -> DataFrame:
        return members.join(labels.withColumnRenamed("node", "key"), "key", "left").withColumn("component", F.coalesce("component", "key"))

    tested = cut(proposed.unionByName(_stars(members.withColumn("component", F.col("key")), None, percent)).distinct())
    near = cut(_similar(tested, sets, percent))
    labels = components(near)
    for _ in range(rounds - 1):
        asks = cut(_stars(cut(told(labels)), tested, percent))
        if asks.isEmpty():
            break
        tested = tested.unionByName(asks)
        near = cut(near.unionByName(_similar(asks, sets, percent)))
        labels = components(near)
    rest = _rest(cut(told(labels)), sets, percent)
    if not rest.isEmpty():
        near = cut(near.unionByName(_links_of_rest(rest, sets, percent)))
        labels = components(near)
    named = nodes.join(labels.withColumnRenamed("node", "key"), "key", "left").select("key", "least", F.coalesce("component", "key").alias("component"))
    roots = named.groupBy("component").agg(F.min("least").alias("component_id"))
    return own.join(named.join(roots, "component").select("key", "component_id"), "key", "left").select(id_column, "component_id")
