"""Exact removal of repeated word windows through compressed FM-indexes, one per shard.

A window is ``width`` consecutive words. Equal windows hold equal word 4-grams, so the smallest hash of a window's
4-grams (its anchor) is the same wherever the window stands. Windows are dealt to shards by anchor, and only those
whose anchor stands at two places or more leave their document: all others are unique already. Consecutive
windows of one anchor travel together as a passage, so a shard's text is a few times the words that may repeat.

A shard puts its passages in order of (document, start), builds an FM-index over their words and streams every
passage through it from right to left. The wavelet matrix answers each backward step; once a match is ``width``
words long, it is shortened by its last word to the enclosing interval before the next step, so the matching
statistics cost one step a word. An interval's smallest text position tells whether the window stands earlier.

Texts whose word sequence is another's are settled without any index: all their windows stand in the first one.
No task gathers the places of a frequent anchor: those with more than 1/HEAVY of all repeated places, HEAVY at most, are
broadcast. Anchors of more than ``hot`` places deal their windows one by one, by the hash of the whole window, so no shard
gathers all contexts of a frequent phrase. A passage that a task has sent before from an earlier place goes whole; the task
sends such passages without their words, those of a document that touch as one, so a shard gets the words of a passage
once a task at most. A shard returns one row for each document.

Null and blank texts have no words. Earlier means a smaller id, or the same id and an earlier start: rows that share an id
remove nothing of each other at the same start, whatever their texts. Null ids come before all others, in an order
that their texts' hashes give, so two null ids are two documents unless their texts are equal. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict
from collections.abc import Iterator
from itertools import count

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shipping import ship
from .common import WordHashes, arrow_map, cut, mix64, read, slices, text_blobs

GRAM = 4
PASSAGE_WINDOWS = 64
SHARD_BYTES = 8 << 20
HEAVY = 1000
FIRST = -(1 << 63)
#: Passages that a task remembers having sent.
REMEMBERED = 300_000


class Bits:
    """Packed bits with one count per 64."""

    def __init__(self, bits: np.ndarray):
        packed = np.packbits(bits, bitorder="little")
        self.words = np.frombuffer(packed.tobytes() + b"\0" * (8 + -len(packed) % 8), np.uint64)
        self.counts = np.concatenate(([0], np.cumsum(np.bitwise_count(self.words), dtype=np.int32)))[: len(self.words)].astype(np.int32)

    def rank(self, at: np.ndarray) -> np.ndarray:
        """Ones before each position."""
        cell = at >> 6
        return self.counts[cell] + np.bitwise_count(self.words[cell] & ((np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)))


class Groups:
    """Runs of equal neighbours: a bit where each begins, and the beginnings."""

    def __init__(self, keys: np.ndarray):
        new = np.concatenate(([True], keys[1:] != keys[:-1]))
        self.begins, self.starts = Bits(new), np.append(np.flatnonzero(new), len(keys)).astype(np.int32)

    def of(self, rows: np.ndarray) -> np.ndarray:
        return self.begins.rank(rows + 1) - 1


class FMIndex:
    """Order-``depth`` FM-index over word numbers; 0 separates texts and stands at both ends.

    Rows are sorted by their first ``depth`` words, which is all that patterns up to that length need. The
    Burrows-Wheeler sequence is a wavelet matrix of packed bits with one count per 64. Besides it the index keeps, of the rows
    that share ``depth`` words and of those that share one less, where each group begins, as bits and 32-bit numbers, and
    of the former the smallest ``age`` (by default the position in the text).
    """

    def __init__(self, tokens: np.ndarray, depth: int, age: np.ndarray | None = None):
        self.tokens, self.depth, n = tokens.astype(np.int32), depth, len(tokens)
        sigma = int(tokens.max()) + 1
        ranks, built = tokens.astype(np.int64), 1
        shorter = ranks if depth == 2 else np.zeros(n, np.int64)
        while built < depth:
            step = min(built, depth - built)
            if built + step == depth:
                shorter = self._longer(ranks, step - 1) if step > 1 else ranks
            ranks, built = self._longer(ranks, step), built + step
        rows = np.argsort(ranks, kind="stable")
        self.same = Groups(ranks[rows])  # of rows that share depth words
        self.outer = Groups(shorter[rows])  # and that share depth - 1 words
        self.earliest = np.minimum.reduceat(rows if age is None else age[rows], self.same.starts[:-1])
        seq = tokens[rows - 1].astype(np.uint32)
        self.levels = []
        base = np.zeros(sigma, np.int64)
        symbols = np.arange(sigma, dtype=np.uint32)
        for shift in range(max(1, (sigma - 1).bit_length()) - 1, -1, -1):
            bit = (seq >> np.uint32(shift)) & np.uint32(1)
            self.levels.append((np.uint32(shift), Bits(bit.astype(np.uint8)), n - int(bit.sum())))
            base = self._step(self.levels[-1], symbols, base)
            ones = bit == 1
            seq = np.concatenate((seq[~ones], seq[ones]))
        before = np.concatenate(([0], np.cumsum(np.bincount(tokens, minlength=sigma))))[:sigma]
        self.shift = before - base

    @staticmethod
    def _longer(ranks: np.ndarray, step: int) -> np.ndarray:
        shifted = np.zeros_like(ranks)
        shifted[:-step] = ranks[step:] + 1
        return np.unique(ranks * (int(ranks.max()) + 2) + shifted, return_inverse=True)[1]

    @staticmethod
    def _step(level, symbols: np.ndarray, at: np.ndarray) -> np.ndarray:
        shift, bits, zeros = level
        ones = bits.rank(at)
        return np.where((symbols >> shift) & np.uint32(1), zeros + ones, at - ones)

    def back(self, symbols: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Intervals of the patterns with one more word in front."""
        both, twice = np.concatenate((low, high)), np.concatenate((symbols, symbols)).astype(np.uint32)
        for level in self.levels:
            both = self._step(level, twice, both)
        both = both + self.shift[twice]
        return both[: len(low)], both[len(low) :]

    def count(self, pattern: np.ndarray) -> int:
        """How often a pattern of at most ``depth`` words stands in the text."""
        low, high = np.array([0]), np.array([len(self.tokens)])
        for c in pattern[::-1]:
            if c >= len(self.shift):
                return 0
            low, high = self.back(np.array([c]), low, high)
        return max(0, int(high[0] - low[0]))

    def stream(self, begins: np.ndarray, lengths: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Matching statistics of pieces of the indexed text, from right to left and side by side.

        Yields (position, low, high) of every place where ``depth`` words match. Rows low to high are one group of ``same``.
        """
        order = np.argsort(-lengths, kind="stable")
        ends, sizes = (begins + lengths - 1)[order], lengths[order]
        low, high = np.zeros(len(order), np.int64), np.full(len(order), len(self.tokens), np.int64)
        for t in range(int(sizes[0]) if len(sizes) else 0):
            n = int(np.searchsorted(-sizes, -t, side="left"))
            low, high, at = low[:n], high[:n], ends[:n] - t
            if t >= self.depth:
                group = self.outer.of(low)
                low, high = self.outer.starts[group].astype(np.int64), self.outer.starts[group + 1].astype(np.int64)
            low, high = self.back(self.tokens[at], low, high)
            if t >= self.depth - 1:
                yield at, low, high


def grams(words: np.ndarray) -> np.ndarray:
    """Hashes of all word 4-grams of a run of word hashes."""
    n = len(words) - GRAM + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.zeros(n, np.uint64)
    for k in range(GRAM):
        h = h * np.uint64(0x9E3779B97F4A7C15) + words[k : k + n]
    return mix64(h)


def _slide(a: np.ndarray, width: int, pick) -> np.ndarray:
    """pick (minimum or maximum) over each ``width`` neighbours."""
    size = 1
    while 2 * size <= width:
        a, size = pick(a[:-size], a[size:]), 2 * size
    return pick(a[: len(a) - (width - size)], a[width - size :]) if width > size else a


def anchors(words: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(anchor of each window, hashes at all places that are some window's anchor)."""
    if len(words) < width:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    g, span = grams(words), width - GRAM + 1
    least = _slide(g, span, np.minimum)
    pad = np.zeros(span - 1, np.uint64)
    return least, g[_slide(np.concatenate((pad, least, pad)), span, np.maximum) == g]


def among(hashes: np.ndarray, signed: list[int]) -> np.ndarray:
    """Which hashes are in a list of them."""
    if not signed:
        return np.zeros(len(hashes), bool)
    known = np.sort(np.array(signed, np.int64).view(np.uint64))
    return known[np.minimum(np.searchsorted(known, hashes), len(known) - 1)] == hashes


def _own(id_column: str, text: str) -> tuple[Column, Column]:
    """The id that orders a row's document (of null ids, one that their text gives), and what tells apart rows that share it."""
    row = F.xxhash64(F.coalesce(F.col(text).cast("string"), F.lit("")))
    return F.coalesce(F.col(id_column).cast("long"), F.lit(FIRST) + F.shiftrightunsigned(row, 2)).alias("_id"), row.alias("_row")


def _early(df: DataFrame, id_column: str, text: str) -> DataFrame:
    """_own() and the text, clash-free, and whether the row has an id."""
    return df.select(*_own(id_column, text), F.col(id_column).isNotNull().alias("_known"), F.col(text).cast("string").alias("text"))


def outline(docs: DataFrame, width: int) -> DataFrame:
    """_id, _row, _known, n_words, sha (of the words joined by a space) and the anchors of each document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in slices(batches):
            counts, shas, found = [], [], []
            for data in text_blobs(batch):
                words = data.split()
                counts.append(len(words))
                shas.append(hashlib.sha256(b" ".join(words)).hexdigest())
                found.append(anchors(hashes.of(words), width)[1].view(np.int64) if len(words) >= width else np.zeros(0, np.int64))
            sizes = np.cumsum([0, *map(len, found)])
            lists = pa.ListArray.from_arrays(pa.array(sizes, pa.int32()), pa.array(np.concatenate(found)))
            yield pa.RecordBatch.from_arrays([batch.column("_id"), batch.column("_row"), batch.column("_known"), pa.array(counts, pa.int32()), pa.array(shas), lists], ["_id", "_row", "_known", "n_words", "sha", "anchors"])

    return arrow_map(docs.select("_id", "_row", "_known", "text"), run, "_id long, _row long, _known boolean, n_words int, sha string, anchors array<long>")


def joined(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The same words in as few spans as can be, in order."""
    out: list[tuple[int, int]] = []
    for start, stop in sorted(spans):
        if out and start <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], stop))
        else:
            out.append((start, stop))
    return out


def _passages(docs: DataFrame, width: int, shards: int) -> DataFrame:
    """Passages of the documents' repeated anchors; ``body`` is null where the task has sent all of it from earlier places."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        sent: dict[bytes, tuple[int, int]] = {}  # digest of a body -> the earliest place it was sent from
        for batch in slices(batches):
            rows: list[tuple] = []
            ids, versions = batch.column("_id").to_pylist(), batch.column("_row").to_pylist()
            wanted, hot = batch.column("repeated").to_pylist(), batch.column("hot").to_pylist()
            if len(sent) > REMEMBERED:
                sent.clear()
            for i, data in sorted(enumerate(text_blobs(batch)), key=lambda x: ids[x[0]]):
                words = data.split()
                own = hashes.of(words)
                least = anchors(own, width)[0]
                if not len(least):
                    continue
                ok = among(least, wanted[i])
                if not ok.any():
                    continue
                apart = among(least, hot[i])
                starts = np.flatnonzero(ok & np.concatenate(([True], (least[1:] != least[:-1]) | ~ok[:-1] | apart[1:])))
                stops = np.flatnonzero(ok & np.concatenate(((least[1:] != least[:-1]) | ~ok[1:] | apart[:-1], [True]))) + 1
                whole: list[tuple[int, int]] = []
                for s, e in zip(starts.tolist(), stops.tolist(), strict=True):
                    for at in range(s, e, PASSAGE_WINDOWS):
                        end = min(e, at + PASSAGE_WINDOWS)
                        body = b" ".join(words[at : end + width - 1])
                        digest, place = xxhash.xxh3_128_digest(body), (ids[i], at)
                        if digest in sent and sent[digest] < place:
                            whole.append((at, end + width - 1))
                            continue
                        sent[digest] = place
                        route = xxhash.xxh64_intdigest(own[at : at + width].tobytes()) if apart[s] else int(least[s])
                        rows.append((route % shards, ids[i], versions[i], at, end - at, body))
                route = xxhash.xxh64_intdigest(b"%d %d" % (ids[i], versions[i]))
                rows += [(route % shards, ids[i], versions[i], a, b - a - width + 1, None) for a, b in joined(whole)]
            if rows:
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], ["shard", "_id", "_row", "start", "windows", "body"])

    return arrow_map(docs.select("_id", "_row", "text", "repeated", "hot"), run, "shard long, _id long, _row long, start int, windows int, body binary")


def shard_repeats(pdf: pd.DataFrame, width: int) -> pd.DataFrame:
    """Word spans of one shard's passages that stand earlier in the shard, a row a document: _id, _row, starts, stops.

    Passages without a body go whole.
    """
    pdf = pdf.sort_values(["_id", "start", "_row"], kind="stable", ignore_index=True)
    ids, starts, windows = pdf["_id"].to_numpy(), pdf["start"].to_numpy().astype(np.int64), pdf["windows"].to_numpy().astype(np.int64)
    bodies, first = pdf["body"].tolist(), {}
    known = np.array([first.setdefault(b, i) if b is not None else -1 for i, b in enumerate(bodies)], np.int64)
    places = list(zip(ids.tolist(), starts.tolist(), strict=True))
    hits = {i: [(int(starts[i]), int(starts[i] + windows[i]) + width - 1)] for i, k in enumerate(known.tolist()) if k < 0 or places[k] < places[i]}
    unique = np.fromiter(first.values(), np.int64, len(first))
    if len(unique):
        sizes = windows[unique] + width - 1
        begins = np.cumsum(sizes + 1) - sizes  # a separator stands before each passage and after the last
        numbers: dict[bytes, int] = defaultdict(count(1).__next__)
        words = b" ".join([bodies[i] for i in unique]).split()
        flat = np.zeros(int(sizes.sum()) + len(sizes) + 1, np.int64)
        inside = np.ones(len(flat), bool)
        inside[begins - 1] = inside[-1] = False
        flat[inside] = np.fromiter(map(numbers.__getitem__, words), np.int64, len(words))
        # a word's age: its document's place in the order of ids, then where it stands in the document
        document = np.unique(ids[unique], return_inverse=True)[1]
        age = np.zeros(len(flat), np.int64)
        age[inside] = np.repeat((document << 32) + starts[unique] - begins, sizes) + np.flatnonzero(inside)
        index = FMIndex(flat, width, age)
        earlier = np.zeros(len(flat), bool)
        for at, low, high in index.stream(begins, sizes):
            many = high - low > 1
            earlier[at[many]] = index.earliest[index.same.of(low[many])] < age[at[many]]
        found = np.flatnonzero(earlier)
        owner = np.searchsorted(begins, found, side="right") - 1
        for k in np.unique(owner):
            i = int(unique[k])
            own = found[np.searchsorted(owner, k) : np.searchsorted(owner, k, side="right")]
            own = own - begins[k] + starts[i]
            cuts = np.flatnonzero(np.diff(own) > width)
            hits[i] = list(zip(own[np.concatenate(([0], cuts + 1))].tolist(), (own[np.concatenate((cuts, [len(own) - 1]))] + width).tolist(), strict=True))
        for i in np.flatnonzero((known >= 0) & (known != np.arange(len(known)))).tolist():
            if i not in hits and int(known[i]) in hits:  # an equal passage of the same age
                hits[i] = hits[int(known[i])]
    versions = pdf["_row"].tolist()
    spans: dict[tuple[int, int], list[tuple[int, int]]] = defaultdict(list)
    for i in sorted(hits):
        spans[places[i][0], versions[i]] += hits[i]
    found = [joined(s) for s in spans.values()]
    return pd.DataFrame({
        "_id": np.array([d for d, _ in spans], np.int64), "_row": np.array([r for _, r in spans], np.int64),
        "starts": pd.Series([[a for a, _ in s] for s in found], dtype=object),
        "stops": pd.Series([[b for _, b in s] for s in found], dtype=object),
    })


def repeated_spans(docs: DataFrame, sketch: DataFrame, width: int, hot: int = 4_096) -> DataFrame:
    """_id, _row and the word spans of windows that stand earlier, for documents that are no copies of earlier ones.

    docs: as _early() gives them. sketch: outline(docs) with ``copy``.
    """
    places = sketch.where(~F.col("copy")).select("_id", "_row", F.explode("anchors").alias("anchor"))
    counted = cut(places.groupBy("anchor").agg(F.count(F.lit(1)).alias("n")).where("n > 1"))
    repeats = counted.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    # an anchor with its share of all repeated places: at most HEAVY of them, so they are broadcast and not shuffled to one task
    heavy = F.col("n") * HEAVY > repeats
    told = places.join(F.broadcast(counted.where(heavy)), "anchor", "left")
    both = told.where("n is not null").unionByName(told.where("n is null").drop("n").join(counted.where(~heavy), "anchor").select(told.columns))
    found = both.groupBy("_id", "_row").agg(F.collect_set("anchor").alias("repeated"), F.collect_set(F.when(F.col("n") > hot, F.col("anchor"))).alias("hot"))
    found = cut(found)
    total = found.agg(F.coalesce(F.sum(F.size("repeated")), F.lit(0))).first()[0]
    shards = max(1, -(-total * 200 // SHARD_BYTES))
    passages = _passages(docs.join(found, ["_id", "_row"]), width, shards)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return shard_repeats(pdf, width)

    ship(docs.sparkSession)
    spans = passages.groupBy("shard").applyInPandas(run, "_id long, _row long, starts array<int>, stops array<int>")
    return spans.groupBy("_id", "_row").agg(F.flatten(F.collect_list("starts")).alias("starts"), F.flatten(F.collect_list("stops")).alias("stops"))


def removed_mask(n: int, starts, stops) -> np.ndarray:
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, np.asarray(starts, np.int64), 1)
    np.add.at(edge, np.asarray(stops, np.int64), -1)
    return np.cumsum(edge)[:n] > 0


def _apply(docs: DataFrame) -> DataFrame:
    """n_removed, the kept words' digest and the kept text of documents with spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            starts, stops = batch.column("starts").to_pylist(), batch.column("stops").to_pylist()
            gone, shas, texts = [], [], []
            for i, data in enumerate(text_blobs(batch)):
                words = data.split()
                mask = removed_mask(len(words), starts[i], stops[i])
                kept = b" ".join([w for w, m in zip(words, mask.tolist(), strict=True) if not m])
                gone.append(int(mask.sum()))
                shas.append(hashlib.sha256(kept).hexdigest())
                texts.append(kept.decode("utf-8"))
            yield pa.RecordBatch.from_arrays([batch.column("_id"), batch.column("_row"), pa.array(gone, pa.int32()), pa.array(shas), pa.array(texts)], ["_id", "_row", "n_removed", "kept_sha256", "kept_text"])

    return arrow_map(docs.select("_id", "_row", "text", "starts", "stops"), run, "_id long, _row long, n_removed int, kept_sha256 string, kept_text string")


def survey(df: DataFrame, width: int = 20, id_column: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame, DataFrame]:
    """(documents, their outlines with ``copy``, spans): what both uses below start from."""
    docs = _early(df, id_column, text)
    sketch = cut(outline(docs, width))
    groups = sketch.where(F.col("n_words") >= width).groupBy("sha").agg(F.min("_id").alias("_least"), F.count(F.lit(1)).alias("_n")).where("_n > 1").select("sha", "_least")
    sketch = cut(sketch.join(groups, "sha", "left").withColumn("copy", F.coalesce(F.col("_id") > F.col("_least"), F.lit(False))).drop("_least"))
    spans = cut(repeated_spans(docs, sketch, width))
    return docs, sketch.drop("anchors"), spans


def window_removal(df: DataFrame, width: int = 20, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """id, n_words, n_removed and kept_sha256 of every document."""
    docs, sketch, spans = survey(df, width, id_column, text)
    cutted = cut(_apply(docs.join(spans, ["_id", "_row"])).drop("kept_text").distinct())
    empty = hashlib.sha256(b"").hexdigest()
    out = sketch.join(cutted, ["_id", "_row"], "left")
    return out.select(
        F.when(F.col("_known"), F.col("_id")).alias(id_column),
        F.col("n_words").cast("long").alias("n_words"),
        F.when(F.col("copy"), F.col("n_words")).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
        F.when(F.col("copy"), F.lit(empty)).otherwise(F.coalesce("kept_sha256", "sha")).alias("kept_sha256"),
    )


def without_repeats(df: DataFrame, width: int = 20, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of ``df`` with repeated windows taken out of their texts; unaffected texts stay as they are."""
    docs, sketch, spans = survey(df, width, id_column, text)
    changed = _apply(docs.join(spans, ["_id", "_row"])).select("_id", "_row", "kept_text").dropDuplicates(["_id", "_row"])
    copies = sketch.where("copy").select("_id", "_row", F.lit("").alias("kept_text")).distinct()
    edits = cut(changed.join(copies, ["_id", "_row"], "left_anti").unionByName(copies))
    keyed = df.select(F.struct(*df.columns).alias("_all"), *_own(id_column, text))
    new = keyed.join(edits, ["_id", "_row"], "left")
    return new.select(*(F.coalesce("kept_text", F.col(f"_all.`{c}`")).alias(c) if c == text else F.col(f"_all.`{c}`") for c in df.columns))


def op8_fm_index_removal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return window_removal(read(spark, sf_dir, "documents"))
