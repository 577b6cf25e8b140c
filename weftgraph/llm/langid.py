"""Language identification of code-switched text with a linear-chain conditional random field.

Every word is labelled. A word's features are the byte n-grams of ``^word$`` up to four bytes long (those that hold
``^`` or ``$`` are its affixes), hashed into a table, and for each language whether the word is in the lexicon that
the fit made. Transition, start and feature weights are learned together: the gradient is that of the
conditional likelihood, by forward-backward. A text's language is the label with the largest summed word
posterior, and its score that label's mean posterior.

Fit: a bounded sample of labelled rows (``fit_rows``, and texts up to ``fit_bytes``), in sequences of segments of two
texts each so that switches occur. No labelled row at all: every prediction is ``und`` with score 0.
Prediction covers whole texts. Null texts and texts without a letter are ``und`` with score 0; repeated rows give
repeated rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, crc_mod, read, slices, with_fields

TABLE_BITS, LONGEST = 16, 4
REMEMBERED = 200_000
#: A slice's word posteriors and messages take some twenty times its text.
SLICE = 2 << 20
UNKNOWN = "und"


def word_features(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(feature, word) index pairs, ordered by word: the hashed n-grams of each bounded word."""
    if not words:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    data = np.frombuffer(b"".join([b"^%b$" % w for w in words]), np.uint8).astype(np.uint32)
    owner = np.repeat(np.arange(len(words)), np.fromiter(map(len, words), np.int64, len(words)) + 2)
    feats, owners, h = [], [], np.zeros(len(data), np.uint32)
    for n in range(1, LONGEST + 1):
        m = len(data) - n + 1
        if m <= 0:
            break
        h = h[:m] * np.uint32(0x01000193) + data[n - 1 :] + np.uint32(n)
        inside = owner[:m] == owner[n - 1 :]
        x = h[inside] * np.uint32(2654435761)
        feats.append((x >> np.uint32(32 - TABLE_BITS)).astype(np.int64))
        owners.append(owner[:m][inside])
    feat, own = np.concatenate(feats), np.concatenate(owners)
    order = np.argsort(own, kind="stable")
    return feat[order], own[order]


def has_letter(word: str) -> bool:
    return any(map(str.isalpha, word))


@dataclass
class Model:
    languages: list[str]
    weights: np.ndarray  # (2**TABLE_BITS + languages, languages): n-grams, then lexicons
    start: np.ndarray
    transition: np.ndarray
    lexicon: dict[int, int] = field(default_factory=dict)  # hash of a word -> bit set of languages

    def emissions(self, words: list[bytes]) -> np.ndarray:
        """(word, language) scores."""
        feat, owner = word_features(words)
        out = np.zeros((len(words), len(self.languages)), np.float32)
        if len(words):
            out += np.add.reduceat(self.weights[feat], np.flatnonzero(np.diff(owner, prepend=-1)), axis=0)
            bits = np.array([self.lexicon.get(xxhash.xxh64_intdigest(w), 0) for w in words], np.int64)
            for k in range(len(self.languages)):
                out[(bits >> k & 1) == 1] += self.weights[(1 << TABLE_BITS) + k]
        return out


def forward_backward(scores: np.ndarray, lengths: np.ndarray, start: np.ndarray, transition: np.ndarray, pairs: bool = False):
    """Posteriors of sequences laid one after another in ``scores``; with ``pairs`` the summed pair posteriors and
    the log partition too. Sequences advance side by side, the longest first, so a step is one vector operation."""
    order = np.argsort(-lengths, kind="stable")
    begins = (np.cumsum(lengths) - lengths)[order]
    sizes = lengths[order]
    k = len(start)
    top = scores.max(axis=1, keepdims=True) if len(scores) else scores
    likely = np.exp(scores - top, dtype=np.float64)
    move, alpha, scale = np.exp(transition.astype(np.float64)), np.empty_like(likely), np.ones(len(scores))
    steps = int(sizes[0]) if len(sizes) else 0
    active = np.searchsorted(-sizes, -np.arange(steps), side="left")
    now = None
    for t in range(steps):
        at = begins[: active[t]] + t
        now = likely[at] * (np.exp(start) if t == 0 else now[: active[t]] @ move)
        s = now.sum(axis=1)
        now /= s[:, None]
        alpha[at], scale[at] = now, s
    beta, expected = np.ones((len(sizes), k)), np.zeros((k, k))
    posterior = np.empty_like(likely)
    for t in range(steps - 1, -1, -1):
        n = active[t]
        at = begins[:n] + t
        if t + 1 < steps:
            m = active[t + 1]
            ahead = likely[at[:m] + 1] * beta[:m] / scale[at[:m] + 1][:, None]
            if pairs:
                expected += (alpha[at[:m]].T @ ahead) * move
            beta[:m] = ahead @ move.T
        posterior[at] = alpha[at] * beta[:n]
    return (posterior, expected, float(np.log(scale).sum() + top.sum())) if pairs else posterior


def fit(texts: list[str], labels: list[str], rounds: int = 60, segment: int = 32, seed: int = 7) -> Model:
    """Fit on whole sample texts' segments: each text gives one run of words from its front, middle and end."""
    languages = sorted(set(labels))
    index = {lang: i for i, lang in enumerate(languages)}
    k = len(languages)
    runs: list[tuple[list[str], int]] = []
    for text, lang in zip(texts, labels, strict=True):
        words = [w for w in text.lower().split() if has_letter(w)]
        if words:
            mid = max(0, len(words) // 2 - segment // 2)
            runs.append((words[mid : mid + segment] + words[:8] + words[-8:], index[lang]))
    model = Model(languages, np.zeros(((1 << TABLE_BITS) + k, k), np.float32), np.zeros(k), np.zeros((k, k)))
    if not runs:
        return model
    counts: dict[str, np.ndarray] = {}
    for words, lang in runs:
        for w in words:
            counts.setdefault(w, np.zeros(k))[lang] += 1
    for w, c in counts.items():
        if c.sum() >= 3:
            model.lexicon[xxhash.xxh64_intdigest(w.encode("utf-8", "surrogatepass"))] = sum(1 << i for i in range(k) if c[i] >= 0.2 * c.sum())
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(runs))
    sequences = [[runs[i] for i in order[j : j + 2]] for j in range(0, len(order), 2)]
    vocabulary = {w: i for i, w in enumerate(counts)}
    token = np.array([vocabulary[w] for s in sequences for words, _ in s for w in words])
    truth = np.array([lang for s in sequences for words, lang in s for _ in words])
    lengths = np.array([sum(len(words) for words, _ in s) for s in sequences])
    firsts = np.cumsum(lengths) - lengths
    words = [w.encode("utf-8", "surrogatepass") for w in vocabulary]
    feat, owner = word_features(words)
    bits = np.array([model.lexicon.get(xxhash.xxh64_intdigest(w), 0) for w in words], np.int64)
    for i in range(k):
        own = np.flatnonzero(bits >> i & 1)
        feat, owner = np.concatenate((feat, np.full(len(own), (1 << TABLE_BITS) + i))), np.concatenate((owner, own))
    right = np.zeros((len(vocabulary), k))
    np.add.at(right, (token, truth), 1)
    same = np.ones(len(token), bool)
    same[firsts] = False
    seen = np.zeros((k, k))
    np.add.at(seen, (truth[:-1][same[1:]], truth[1:][same[1:]]), 1)
    began = np.bincount(truth[firsts], minlength=k)
    n = len(token)
    params = [model.weights.astype(np.float64), model.start, model.transition]
    first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    for step in range(1, rounds + 1):
        weights, start, transition = params
        word_scores = np.stack([np.bincount(owner, weights[feat, i], len(vocabulary)) for i in range(k)], axis=1)
        posterior, expected, _ = forward_backward(word_scores[token], lengths, start, transition, pairs=True)
        guess = np.stack([np.bincount(token, posterior[:, i], len(vocabulary)) for i in range(k)], axis=1)
        gap = right - guess
        gradient = [
            np.stack([np.bincount(feat, gap[owner, i], len(weights)) for i in range(k)], axis=1) - 0.5 * weights,
            began - posterior[firsts].sum(axis=0) - 0.5 * start,
            seen - expected - 0.5 * transition,
        ]
        for p, g, a, b in zip(params, gradient, first, second, strict=True):
            g = g / n
            a += 0.1 * (g - a)
            b += 0.01 * (g * g - b)
            p += 0.1 * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.99**step)) + 1e-8)
    model.weights, model.start, model.transition = params[0].astype(np.float32), params[1], params[2]
    return model


class Labeller:
    """Labels texts with a model; remembers the scores of words seen before."""

    def __init__(self, model: Model):
        self.model, self.known, self.fresh = model, {}, []
        self.table = np.zeros((1, len(model.languages)), np.float32)

    def _ids(self, words: list[str]) -> np.ndarray:
        try:
            return np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))
        except KeyError:
            for w in words:
                if w not in self.known:
                    if has_letter(w):
                        self.fresh.append(w.encode("utf-8", "surrogatepass"))
                        self.known[w] = len(self.table) - 1 + len(self.fresh)
                    else:
                        self.known[w] = 0
            return np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))

    def words(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Posteriors of all words, number of words of each text, and whether each text has a letter."""
        if len(self.known) > REMEMBERED:
            self.known, self.table = {}, self.table[:1]
        ids = [self._ids((t or "").lower().split()) for t in texts]
        if self.fresh:
            self.table = np.concatenate((self.table, self.model.emissions(self.fresh)))
            self.fresh = []
        lengths = np.array([len(i) for i in ids], np.int64)
        letters = np.array([bool(i.any()) for i in ids], bool)
        flat = np.concatenate(ids) if ids else np.zeros(0, np.int64)
        return forward_backward(self.table[flat], lengths, self.model.start, self.model.transition), lengths, letters

    def texts(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        langs, scores = [UNKNOWN] * len(texts), [0.0] * len(texts)
        if not self.model.languages:
            return langs, scores
        posterior, lengths, letters = self.words(texts)
        ends = np.cumsum(lengths)
        for i in np.flatnonzero(letters):
            mean = posterior[ends[i] - lengths[i] : ends[i]].mean(axis=0)
            best = int(mean.argmax())
            langs[i], scores[i] = self.model.languages[best], float(min(1.0, mean[best]))
        return langs, scores


def sample(df: DataFrame, ids: Column, rows: int) -> DataFrame:
    """About ``rows`` rows by a hash of their id, twice as many at the very most."""
    n = df.count()
    share = min(1.0, rows / n) if n else 1.0
    return df.where(F.pmod(F.xxhash64(ids), F.lit(1 << 20)) < int(share * (1 << 20)) + 1).limit(2 * rows)


def train(docs: DataFrame, fit_rows: int = 1500, fit_bytes: int = 20_000) -> Model:
    """Fit on a sample of rows that have text and lang; the caller leaves out what must not be learned from."""
    able = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    got = sample(able, F.col("doc_id"), fit_rows).where(F.octet_length("text") <= fit_bytes).select("doc_id", "text", "lang").toPandas()
    got = got.sort_values(["doc_id", "text"], ignore_index=True)
    return fit(got["text"].tolist(), got["lang"].tolist())


def predict(df: DataFrame, model: Model, text: str = "text", keep: tuple[str, ...] = ("doc_id",), names: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """``keep`` columns, then the language and its score under ``names``."""
    shared = df.sparkSession.sparkContext.broadcast(model)  # size set by TABLE_BITS and the number of languages
    schema = with_fields(df, keep, f"`{names[0]}` string, `{names[1]}` double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labeller = Labeller(shared.value)
        for batch in slices(batches, text, SLICE):
            langs, scores = labeller.texts(batch.column(text).to_pylist())
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keep), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], [*keep, *names])

    return arrow_map(df.select(*dict.fromkeys([*keep, text])), run, schema)


def label_words(df: DataFrame, model: Model, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """One row per word: id, position, word, its most likely language and that posterior."""
    shared = df.sparkSession.sparkContext.broadcast(model)  # size set by TABLE_BITS and the number of languages

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labeller = Labeller(shared.value)
        for batch in slices(batches, text, SLICE):
            texts = batch.column(text).to_pylist()
            posterior, lengths, _ = labeller.words(texts)
            best = posterior.argmax(axis=1)
            rows = pd.DataFrame({"position": np.concatenate([np.arange(n) for n in lengths]) if len(lengths) else [], "word": [w for t in texts for w in (t or "").lower().split()]})
            ids = np.repeat(np.arange(len(texts)), lengths)
            yield pa.RecordBatch.from_arrays(
                [batch.column(id_column).take(pa.array(ids)), pa.array(rows["position"], pa.int32(), from_pandas=True), pa.array(rows["word"], pa.string()), pa.array([labeller.model.languages[b] for b in best], pa.string()), pa.array(posterior[np.arange(len(best)), best])],
                [id_column, "position", "word", "lang", "posterior"],
            )

    kind = df.schema[id_column].dataType.simpleString()
    return arrow_map(df.select(id_column, text), run, f"`{id_column}` {kind}, position int, word string, lang string, posterior double")


def op7_crf_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), "lang")
    part = crc_mod("doc_id", 3)
    model = train(docs.where(part != 1))
    return predict(docs, model).select("doc_id", (crc_mod("doc_id", 3) == 1).alias("held_out"), "lang_pred", "score")
