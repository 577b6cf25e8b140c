"""Stupid-backoff language-model scores of every document, with n-gram counts of the whole corpus.

The corpus is read once into blocks: a row holds some documents' words as numbers into the block's own vocabulary.
Per order, each block sends its distinct n-grams, as 64-bit hashes in hash order, to the count tables, which are
partitioned by hash range. A range adds up what all blocks sent and answers each with the totals of its n-grams, in
the same order. Joined to its answers, a block scores its documents and sums per document. Since a block sends an
n-gram once however often it has it, no hash is hot, and what moves grows with the corpus.

A word's score is f(n-gram) / f(its context) for the longest n-gram ending there whose count reaches ``least``,
times ``alpha`` per order given up from the longest that the position has; the last resort is the word's share of all
words. Scores are natural logarithms. Words are runs without ASCII white space, as they are.

Null and blank texts have no words and score 0. Repeated rows count, and are scored, as often as they occur. Other
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shipping import ship
from .common import WordHashes, arrow_map, cut, mix64, read, slices, text_blobs

BLOCK_WORDS = 1 << 20
RANGE_NGRAMS = 1 << 21
_STEP = np.uint64(0x9E3779B97F4A7C15)


def _pack(a: np.ndarray) -> bytes:
    return pa.compress(a.tobytes(), "zstd", asbytes=True)


def _unpack(data: bytes, kind, n: int) -> np.ndarray:
    return np.frombuffer(pa.decompress(data, n * np.dtype(kind).itemsize, "zstd", asbytes=True), kind)


def blocks(docs: DataFrame) -> DataFrame:
    """block, documents and words of it, and packed: ids, lengths, vocabulary hashes, word numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, part, made = WordHashes(), TaskContext.get().partitionId(), 0
        ids: list = []
        words: list[np.ndarray] = []
        held = 0

        def flush() -> pa.RecordBatch:
            flat = np.concatenate(words)
            vocabulary, numbers = np.unique(flat, return_inverse=True)
            own = np.array([i is not None for i in ids])
            row = [
                [(part << 32) + made], [len(ids)], [len(flat)], [len(vocabulary)], [_pack(np.array([i or 0 for i in ids], np.int64))], [_pack(own)],
                [_pack(np.fromiter(map(len, words), np.int32, len(words)))], [vocabulary.tobytes()], [_pack(numbers.astype(np.int32))],
            ]
            kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), *[pa.binary()] * 5]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(row, kinds, strict=True)], ["block", "docs", "words", "distinct", "ids", "known", "lengths", "vocabulary", "numbers"])

        for batch in slices(batches):
            for i, data in zip(batch.column("doc_id").to_pylist(), text_blobs(batch), strict=True):
                ids.append(i)
                words.append(hashes.of(data.split()))
                held += len(words[-1])
                if held >= BLOCK_WORDS or len(ids) >= BLOCK_WORDS:
                    yield flush()
                    ids, words, held, made = [], [], 0, made + 1
        if ids:
            yield flush()

    return arrow_map(docs.select("doc_id", "text"), run, "block long, docs int, words int, distinct int, ids binary, known binary, lengths binary, vocabulary binary, numbers binary")


class Block:
    """An unpacked block row."""

    def __init__(self, row: dict):
        n = row["words"]
        self.ids = _unpack(row["ids"], np.int64, row["docs"])
        self.known = _unpack(row["known"], np.bool_, row["docs"])
        self.lengths = _unpack(row["lengths"], np.int32, row["docs"]).astype(np.int64)
        self.hashes = np.frombuffer(row["vocabulary"], np.uint64)[_unpack(row["numbers"], np.int32, n)]
        starts = np.repeat(np.cumsum(self.lengths) - self.lengths, self.lengths)
        self.place = np.arange(n) - starts  # of each word in its document

    def ngrams(self, order: int) -> np.ndarray:
        """Hash of the n-gram ending at each word that has one."""
        h = np.zeros(max(0, len(self.hashes) - order + 1), np.uint64)
        for k in range(order):
            h = h * _STEP + self.hashes[k : len(self.hashes) - order + 1 + k]
        return (mix64(h) if order > 1 else h)[self.place[order - 1 :] >= order - 1]


def totals(store: DataFrame, order: int, ranges: int) -> DataFrame:
    """block, order, range and the counts in the corpus of the block's distinct n-grams of that hash range, in hash order."""
    bits = max(0, (ranges - 1).bit_length())

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                grams, counts = np.unique(Block(row).ngrams(order), return_counts=True)
                edges = np.searchsorted(grams, np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits)) if bits else np.zeros(0, np.int64)
                edges = np.concatenate(([0], edges, [len(grams)]))
                full = np.flatnonzero(np.diff(edges))
                cols = [full, np.full(len(full), row["block"]), np.diff(edges)[full], [grams[edges[k] : edges[k + 1]].tobytes() for k in full], [_pack(counts[edges[k] : edges[k + 1]].astype(np.int32)) for k in full]]
                kinds = [pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["range", "block", "n", "grams", "counts"])

    def add(pdf: pd.DataFrame) -> pd.DataFrame:
        sizes = pdf["n"].to_numpy()
        grams = np.frombuffer(b"".join(pdf["grams"]), np.uint64)
        counts = np.concatenate([_unpack(c, np.int32, n) for c, n in zip(pdf["counts"], sizes, strict=True)])
        _, back = np.unique(grams, return_inverse=True)
        total = np.bincount(back, counts).astype(np.int64)[back]
        ends = np.cumsum(sizes)
        return pd.DataFrame({"block": pdf["block"], "range": pdf["range"], "n": sizes, "total": [_pack(total[e - n : e]) for e, n in zip(ends, sizes, strict=True)]})

    sent = arrow_map(store, send, "range int, block long, n int, grams binary, counts binary")
    answered = sent.groupBy("range").applyInPandas(add, "block long, range int, n int, total binary")
    return answered.select("block", F.lit(order).alias("gram"), "range", "n", "total")


def score_block(block: Block, counts: dict[int, np.ndarray], order: int, all_words: int, alpha: float, least: int) -> np.ndarray:
    """The log score of each document; counts: of the block's distinct n-grams in hash order, for each order."""
    n = len(block.hashes)
    seen = {}  # order -> count of the n-gram ending at each word, 0 where there is none
    for k in range(1, order + 1):
        at = np.zeros(n, np.int64)
        at[block.place >= k - 1] = counts[k][np.unique(block.ngrams(k), return_inverse=True)[1]] if len(counts[k]) else 0
        seen[k] = at
    longest = np.minimum(block.place + 1, order)
    score = np.log(np.maximum(seen[1], 1) / max(1, all_words)) + (longest - 1) * np.log(alpha)
    for k in range(2, order + 1):
        use = (block.place >= k - 1) & (seen[k] >= least)
        context = np.concatenate(([0], seen[k - 1][:-1]))
        score[use] = np.log(seen[k][use] / context[use]) + (longest[use] - k) * np.log(alpha)
    doc = np.repeat(np.arange(len(block.ids)), block.lengths)
    return np.bincount(doc, score, len(block.ids))


def backoff_scores(df: DataFrame, order: int = 3, alpha: float = 0.4, least: int = 2, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_words, log_score (summed over the words) and mean_score of every row."""
    docs = df.select(F.col(id_column).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    ship(df.sparkSession)
    store = cut(blocks(docs))
    all_words = store.agg(F.coalesce(F.sum("words"), F.lit(0))).first()[0]
    ranges = max(1, -(-all_words // RANGE_NGRAMS))
    answers = [cut(totals(store, k, ranges)) for k in range(1, order + 1)]
    joined = store.withColumns({"gram": F.lit(0), "range": F.lit(0), "n": F.lit(0), "total": F.lit(None).cast("binary")})
    for a in answers:
        joined = joined.unionByName(a, allowMissingColumns=True)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        row = pdf[pdf["gram"] == 0].iloc[0].to_dict()
        block = Block({k: int(v) if k in ("words", "docs") else v for k, v in row.items()})
        counts = {}
        for k in range(1, order + 1):
            own = pdf[pdf["gram"] == k].sort_values("range")
            counts[k] = np.concatenate([_unpack(t, np.int64, n) for t, n in zip(own["total"], own["n"], strict=True)] or [np.zeros(0, np.int64)])
        total = score_block(block, counts, order, all_words, alpha, least)
        ids = pd.array(block.ids, "Int64")
        ids[~block.known] = pd.NA
        return pd.DataFrame({"doc_id": ids, "n_words": block.lengths, "log_score": total, "mean_score": total / np.maximum(block.lengths, 1)})

    return joined.groupBy("block").applyInPandas(run, "doc_id long, n_words long, log_score double, mean_score double")


def op5_stupid_backoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return backoff_scores(read(spark, sf_dir, "documents")).select("doc_id", "n_words", F.round("log_score", 5).alias("log_score"), F.round("mean_score", 7).alias("mean_score"))


OP5_SQL = """
WITH words AS (
  SELECT d.doc_id, u.w, u.i FROM documents d, unnest(regexp_extract_all(coalesce(d.text, ''), '[^\\x20\\x09-\\x0D]+')) WITH ORDINALITY u(w, i)
), ctx AS (
  SELECT doc_id, i, w, lag(w) OVER o AS v, lag(w, 2) OVER o AS u FROM words WINDOW o AS (PARTITION BY doc_id ORDER BY i)
), c1 AS (SELECT w, count(*) AS n FROM words GROUP BY w),
c2 AS (SELECT v, w, count(*) AS n FROM ctx WHERE v IS NOT NULL GROUP BY v, w),
c3 AS (SELECT u, v, w, count(*) AS n FROM ctx WHERE u IS NOT NULL GROUP BY u, v, w),
total AS (SELECT count(*) AS n FROM words),
scored AS (
  SELECT x.doc_id, CASE
    WHEN c3.n >= 2 THEN ln(c3.n / p2.n)
    WHEN c2.n >= 2 THEN ln(c2.n / p1.n) + CASE WHEN x.u IS NULL THEN 0 ELSE ln(0.4) END
    ELSE ln(c1.n / total.n) + (least(x.i, 3) - 1) * ln(0.4) END AS s
  FROM ctx x JOIN c1 ON c1.w = x.w CROSS JOIN total
  LEFT JOIN c1 p1 ON p1.w = x.v
  LEFT JOIN c2 ON c2.v = x.v AND c2.w = x.w
  LEFT JOIN c2 p2 ON p2.v = x.u AND p2.w = x.v
  LEFT JOIN c3 ON c3.u = x.u AND c3.v = x.v AND c3.w = x.w
)
SELECT d.doc_id, coalesce(s.n, 0)::BIGINT AS n_words, coalesce(round(s.t, 5), 0) AS log_score, coalesce(round(s.t / s.n, 7), 0) AS mean_score
FROM documents d LEFT JOIN (SELECT doc_id, count(*) AS n, sum(s) AS t FROM scored GROUP BY doc_id) s USING (doc_id)
"""
