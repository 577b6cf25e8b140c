"""Quality scores from histogram gradient-boosted trees over document statistics.

Each document's text is turned into the numbers in FEATURES, in vectorised passes over its bytes and words. Trees are grown level by level on binned features, to a fixed depth, and kept as three flat arrays in heap
order, so scoring is one numpy step per level for all trees and rows at once.

Fit: at most twice ``fit_rows`` labelled rows, by a hash of their id. No labelled row, or one class only: every
score is that class's rate (0.5 with none). Null text counts as empty and is scored like any other text; repeated rows
give repeated rows; null labels are not learned from; other columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, crc_mod, cut, read, slices, text_blobs, with_fields
from .langid import sample

CLASSES = {
    "lower": bytes(range(97, 123)), "upper": bytes(range(65, 91)), "digit": b"0123456789", "blank": b" \t\r\x0b\x0c", "line": b"\n",
    "stop": b".,;:?'\"()-", "shout": b"!", "bar": b"|", "mark": b"#$%&*@^~_=+<>/\\[]{}`", "high": bytes(range(128, 256)),
}
FEATURES = [
    "log_bytes", "log_words", "word_bytes", "words_a_line", *(f"share_{k}" for k in CLASSES),
    "distinct_words", "distinct_lines", "top_word", "short_words", "long_words", "closed_lines", "longest_line",
]
_CLASS = np.zeros(256, np.int64)
for _k, _chars in enumerate(CLASSES.values()):
    _CLASS[list(_chars)] = _k + 1


def statistics(texts: list[bytes]) -> np.ndarray:
    """(text, feature) float32."""
    out = np.zeros((len(texts), len(FEATURES)), np.float32)
    if not texts:
        return out
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    kinds = len(CLASSES) + 1
    flat = _CLASS[np.frombuffer(b"".join(texts), np.uint8)] + np.repeat(np.arange(len(texts)) * kinds, sizes)
    shares = np.bincount(flat, minlength=len(texts) * kinds).reshape(-1, kinds)[:, 1:] / np.maximum(sizes, 1)[:, None]
    out[:, 4 : 4 + len(CLASSES)] = shares
    for i, t in enumerate(texts):
        words = t.split()
        lines = [x for x in t.split(b"\n") if x]
        n, m = max(1, len(words)), max(1, len(lines))
        lens = np.fromiter(map(len, words), np.int64, len(words))
        distinct = Counter(words)
        top = max(distinct.values(), default=0)
        out[i, :4] = np.log1p(len(t)), np.log1p(len(words)), lens.sum() / n, len(words) / m
        out[i, 4 + len(CLASSES) :] = (
            len(distinct) / n, len(set(lines)) / m, top / n, (lens <= 3).sum() / n, (lens >= 16).sum() / n,
            sum(x[-1:] in b".?!:;" for x in lines) / m, max(map(len, lines), default=0) / max(1, len(t)),
        )
    return out


@dataclass
class Trees:
    """Complete trees in heap order: node i has children 2i + 1 (value <= threshold) and 2i + 2."""

    base: float
    feature: np.ndarray  # (tree, inner node)
    threshold: np.ndarray  # (tree, inner node)
    value: np.ndarray  # (tree, leaf)

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        inner = self.feature.shape[1] if self.feature.size else 0
        rows = np.arange(len(x))
        for f, t, v in zip(self.feature, self.threshold, self.value, strict=True):
            at = np.zeros(len(x), np.int64)
            while inner and at[0:1].size and at[0] < inner:
                at = 2 * at + 1 + (x[rows, f[at]] > t[at])
            out += v[at - inner]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.raw(np.nan_to_num(x))))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, bins: int = 64, rate: float = 0.15, ridge: float = 2.0) -> Trees:
    inner = 2**depth - 1
    empty = Trees(0.0, np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, inner + 1)))
    if not len(y):
        return empty
    p = float(np.clip(y.mean(), 1e-4, 1 - 1e-4))
    empty.base = float(np.log(p / (1 - p)))
    if y.min() == y.max():
        return empty
    x = np.nan_to_num(x)
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(x.shape[1])]
    binned = np.stack([np.searchsorted(e, x[:, f], side="left") for f, e in enumerate(edges)], axis=1)
    raw, feats, cuts, values = np.full(len(y), empty.base), [], [], []
    for _ in range(trees):
        prob = 1 / (1 + np.exp(-raw))
        g, h = y - prob, prob * (1 - prob)
        at = np.zeros(len(y), np.int64)
        feature, threshold = np.zeros(inner, np.int64), np.full(inner, np.inf)
        for level in range(depth):
            first, n = 2**level - 1, 2**level
            best, gain = np.full((n, 2), -1), np.full(n, 1e-6)
            for f, e in enumerate(edges):
                if not len(e):
                    continue
                cell = (at - first) * bins + binned[:, f]
                gs = np.cumsum(np.bincount(cell, g, n * bins).reshape(n, bins), axis=1)
                hs = np.cumsum(np.bincount(cell, h, n * bins).reshape(n, bins), axis=1)
                all_g, all_h = gs[:, -1:], hs[:, -1:]
                lift = gs**2 / (hs + ridge) + (all_g - gs) ** 2 / (all_h - hs + ridge) - all_g**2 / (all_h + ridge)
                lift[(hs < 1) | (all_h - hs < 1)] = 0
                lift = lift[:, : len(e)]
                k = lift.argmax(axis=1)
                better = lift[np.arange(n), k] > gain
                gain[better] = lift[np.arange(n), k][better]
                best[better] = np.stack((np.full(n, f), k), axis=1)[better]
            for node in range(n):
                if best[node, 0] >= 0:
                    feature[first + node], threshold[first + node] = best[node, 0], edges[best[node, 0]][best[node, 1]]
            at = 2 * at + 1 + (x[np.arange(len(y)), feature[at]] > threshold[at])
        leaf = at - inner
        value = rate * np.bincount(leaf, g, inner + 1) / (np.bincount(leaf, h, inner + 1) + ridge)
        raw += value[leaf]
        feats.append(feature)
        cuts.append(threshold)
        values.append(value)
    return Trees(empty.base, np.array(feats), np.array(cuts), np.array(values))


def features(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns and ``x``, the statistics as array<float>."""
    schema = with_fields(df, keep, "x array<float>")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text):
            x = statistics(text_blobs(batch, text))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * len(FEATURES), pa.int32()), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keep), lists], [*keep, "x"])

    return arrow_map(df.select(*keep, text), run, schema)


def train(docs: DataFrame, labels: DataFrame, fit_rows: int = 20_000) -> Trees:
    """docs: doc_id and text, without those not to learn from; labels: doc_id and quality."""
    marked = labels.where(F.col("quality").isin(0, 1)).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").cast("int").alias("quality"))
    chosen = cut(sample(marked, F.col("doc_id"), fit_rows))  # at most 2 * fit_rows rows of two numbers: broadcast below
    rows = features(docs.join(F.broadcast(chosen), "doc_id").select("doc_id", "text", "quality"), keep=("doc_id", "quality"))
    got = rows.limit(4 * fit_rows).toPandas()
    x = np.array(got["x"].tolist(), np.float32).reshape(-1, len(FEATURES)).astype(np.float64)
    order = np.lexsort((*x.T, got["doc_id"].to_numpy()))
    return fit(x[order], got["quality"].to_numpy(np.float64)[order])


def predict(df: DataFrame, model: Trees, text: str = "text", keep: tuple[str, ...] = ("doc_id",), name: str = "score") -> DataFrame:
    """``keep`` columns and every text's score under ``name``, in one pass."""
    shared = df.sparkSession.sparkContext.broadcast(model)  # size set by the number and depth of trees

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text):
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keep), pa.array(shared.value.score(statistics(text_blobs(batch, text)).astype(np.float64)))], [*keep, name])

    return arrow_map(df.select(*dict.fromkeys([*keep, text])), run, with_fields(df, keep, f"`{name}` double"))


THRESHOLD = 0.3


def op10_quality_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    labels = read(spark, sf_dir, "labels")
    model = train(docs.where(crc_mod("doc_id", 5) != 0), labels.where(crc_mod("doc_id", 5) != 0))
    return predict(docs, model).select("doc_id", (crc_mod("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
