"""Byte-level BPE as a streaming transducer with bounded lookahead, and its incremental decoder.

The merge list fixes how far to the right of a token boundary bytes can still change it. ``sufficient_lookahead``
computes that bound once per merge list; ``WordStream`` keeps that many bytes pending and emits every token that
ends before them. What is left starts at a true token boundary, and no merge crosses one, so encoding goes on from
there with nothing else remembered: memory depends on the merge list, not on the text.

A text goes through ``TextStream`` in chunks of CHUNK bytes, read from the column's buffer: it gives the tokens that no later
chunk can change and keeps the last word and what may become a special text. A word that does not end in the chunk goes on through
its own ``WordStream``. Tokens are counted, digested and decoded as they come. Words met before are looked up in ``Words``.

Null text counts as empty (no ids, empty decoded text); repeated rows give repeated rows.
"""

from __future__ import annotations

import codecs
import hashlib
import heapq
import json
from bisect import bisect_left
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, read, slices, with_fields

#: The word pattern of the byte-level pre-tokenizer (fixed value).
WORD = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
#: Bytes of a text that are taken at once.
CHUNK = 1 << 16
#: A word of more characters than this is not waited for: what has come of it is encoded.
WAITED = 512
#: Words, and characters of them, remembered by one worker before it starts anew.
REMEMBERED, REMEMBERED_CHARS = 400_000, 8_000_000
_NEVER = 1 << 60
#: What a word that is not waited for can go on with: letters, numbers, other marks, white space.
KINDS = [regex.compile(p) for p in (r"\p{L}+", r"\p{N}+", r"[^\p{White_Space}\p{L}\p{N}]+", r"\p{White_Space}+")]


def byte_letters() -> dict[str, int]:
    """The printable stand-in of each byte: printable Latin-1 stands for itself, the rest for 256 and up."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + k): b for k, b in enumerate(rest)}


def sufficient_lookahead(merges: list[tuple[int, int, int]], length: dict[int, int]) -> int:
    """Bytes right of a token boundary that can still decide whether a merge crosses it.

    merges: (left, right, made) ids in order of rank. A merge (s, w) can cross the boundary after s if w forms
    there, and whether w forms depends on what is right of w's own end: on merges of lower rank whose left part is
    a token that at some time ends there, which is w or a token on its right edge while that is not yet merged
    away. Ranks fall at each step, so one pass in order of rank gives the longest such chain.
    """
    rank_of = {made: r for r, (_, _, made) in enumerate(merges)}
    right_of = {made: right for _, right, made in merges}
    ranks: dict[int, list[int]] = {}
    reach: dict[int, list[int]] = {}

    def known(token: int, before: int) -> int:
        rs = ranks.get(token)
        if not rs:
            return 0
        k = bisect_left(rs, before)
        return reach[token][k - 1] if k else 0

    longest = 0
    for q, (left, right, _) in enumerate(merges):
        beyond, token, until = 0, right, q
        while True:
            beyond = max(beyond, known(token, until))
            if token not in rank_of:
                break
            until = min(until, rank_of[token])
            token = right_of[token]
        far = length[right] + beyond
        longest = max(longest, far)
        ranks.setdefault(left, []).append(q)
        reach.setdefault(left, []).append(max(far, reach[left][-1] if left in reach and reach[left] else 0))
    return longest


class Vocabulary:
    """Ids, merges and special texts of a byte-level BPE file of the tokenizers library."""

    def __init__(self, raw: str | bytes):
        spec = json.loads(raw)
        letters = byte_letters()
        ids = spec["model"]["vocab"]
        self.token_bytes = {i: bytes(letters[c] for c in s) for s, i in ids.items() if all(c in letters for c in s)}
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in spec["model"]["merges"]]
        self.merges = [(ids[a], ids[b], ids[a + b]) for a, b in pairs]
        self.rank = {(a, b): r for r, (a, b, _) in enumerate(self.merges)}
        self.made = [m for _, _, m in self.merges]
        by_byte = {b: ids[c] for c, b in letters.items() if c in ids}
        self.byte_id = [by_byte[b] for b in range(256)]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens") or []}
        for text, i in self.special.items():
            self.token_bytes[i] = text.encode()
        self.lookahead = sufficient_lookahead(self.merges, {i: len(b) for i, b in self.token_bytes.items()})
        self.word = regex.compile(WORD)
        self.split = regex.compile("|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True))) if self.special else None

    def merge(self, data: bytes) -> list[int]:
        """The ids of one word: the lowest-ranked pair merges first, the leftmost of equals."""
        if len(data) > WAITED:
            return self._merge_long(data)
        parts = list(map(self.byte_id.__getitem__, data))
        get, made = self.rank.get, self.made
        ranks = [get(p, _NEVER) for p in zip(parts, parts[1:])]
        while ranks:
            r = min(ranks)
            if r == _NEVER:
                break
            i = ranks.index(r)
            parts[i : i + 2] = [made[r]]
            del ranks[i]
            if i:
                ranks[i - 1] = get((parts[i - 1], parts[i]), _NEVER)
            if i < len(ranks):
                ranks[i] = get((parts[i], parts[i + 1]), _NEVER)
        return parts

    def _merge_long(self, data: bytes) -> list[int]:
        """The same over a linked list and a heap."""
        ids: list[int] = [self.byte_id[b] for b in data]
        n = len(ids)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := self.rank.get((ids[i], ids[i + 1]), _NEVER)) != _NEVER]
        heapq.heapify(heap)
        while heap:
            r, i, a, b = heapq.heappop(heap)
            j = after[i]
            if ids[i] != a or j >= n or ids[j] != b:
                continue
            ids[i], ids[j] = self.made[r], -1
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
                if (q := self.rank.get((ids[i], ids[after[i]]), _NEVER)) != _NEVER:
                    heapq.heappush(heap, (q, i, ids[i], ids[after[i]]))
            if (h := before[i]) >= 0 and (q := self.rank.get((ids[h], ids[i]), _NEVER)) != _NEVER:
                heapq.heappush(heap, (q, h, ids[h], ids[i]))
        return [i for i in ids if i >= 0]


class WordStream:
    """Encodes one word that arrives in pieces; ``feed`` returns the ids that have become stable."""

    def __init__(self, vocabulary: Vocabulary):
        self.vocabulary, self.pending = vocabulary, bytearray()
        self.block = max(1024, 2 * vocabulary.lookahead)

    def feed(self, data: bytes) -> list[int]:
        out: list[int] = []
        for at in range(0, len(data), self.block):
            self.pending += data[at : at + self.block]
            if len(self.pending) >= self.block + self.vocabulary.lookahead:
                done, stable = 0, len(self.pending) - self.vocabulary.lookahead
                for i in self.vocabulary.merge(bytes(self.pending)):
                    size = len(self.vocabulary.token_bytes[i])
                    if done + size > stable:
                        break
                    out.append(i)
                    done += size
                del self.pending[:done]
        return out

    def finish(self) -> list[int]:
        out = self.vocabulary.merge(bytes(self.pending))
        self.pending.clear()
        return out


#: What becomes of one word or special text: its ids as decimal text, how many, and their bytes.
Part = tuple[str, int, bytes]


class Words(dict):
    """word -> Part, by a stream of its own; what is remembered is bounded and changes no result."""

    def __init__(self, vocabulary: Vocabulary):
        super().__init__()
        self.vocabulary, self.chars = vocabulary, 0

    def part(self, ids: list[int]) -> Part:
        return ",".join(map(str, ids)), len(ids), b"".join([self.vocabulary.token_bytes[i] for i in ids])

    def __missing__(self, word: str) -> Part:
        stream = WordStream(self.vocabulary)
        made = self.part(stream.feed(word.encode("utf-8", "surrogatepass")) + stream.finish())
        if len(self) >= REMEMBERED or self.chars > REMEMBERED_CHARS:
            self.clear()
            self.chars = 0
        self[word] = made
        self.chars += len(word)
        return made


class TextStream:
    """Encodes a text that arrives in chunks, special texts apart; parts come out once no later chunk can change them."""

    def __init__(self, words: Words):
        self.words, self.vocabulary, self.held, self.inside, self.kind = words, words.vocabulary, "", None, None
        self.keep = max([2, *(len(s) for s in self.vocabulary.special)])

    def feed(self, chunk: str, last: bool = False) -> list[Part]:
        v, out, text, at = self.vocabulary, [], self.held + chunk, 0
        for m in v.split.finditer(text) if v.split else ():
            out += self._words(text[at : m.start()], True)[0]
            out.append((str(v.special[m.group()]), 1, m.group().encode()))
            at = m.end()
        if last:
            out += self._words(text[at:], True)[0]
            self.held = ""
        else:  # the end may be the start of a special text
            free = max(at, len(text) - self.keep)
            parts, rest = self._words(text[at:free], False)
            out += parts
            self.held = rest + text[free:]
        return out

    def finish(self) -> list[Part]:
        return self.feed("", True)

    def _words(self, text: str, whole: bool) -> tuple[list[Part], str]:
        """Parts of the words that are settled, and the text after them; whole: no more of this text will come."""
        v, out, at = self.vocabulary, [], 0
        if self.inside is not None:
            run = self.kind.match(text)
            at = run.end() if run else 0
            ends = whole or at < len(text)
            back = at and ends and self.kind is KINDS[3] and at < len(text)
            if self.kind is KINDS[3] and at == len(text) and not whole:
                at -= bool(at)  # the last space may belong to what follows
                ends = False
            ids = self.inside.feed(text[: at - back].encode("utf-8", "surrogatepass"))
            at -= back
            if ends:
                ids += self.inside.finish()
                self.inside = None
            if ids:
                out.append(self.words.part(ids))
            if not ends:
                return out, text[at:]
        found, end = v.word.findall(text, at), len(text)
        if not whole:  # a word that ends here may go on, and a space before it may belong to what follows
            last = ""
            while found and end > len(text) - 2:
                last = found.pop()
                end -= len(last)
            if len(last) > WAITED:
                out += map(self.words.__getitem__, found)
                self.kind = next(k for k in KINDS if k.match(last[-1]))
                body = last[:-1] if self.kind is KINDS[3] else last
                self.inside = WordStream(v)
                if ids := self.inside.feed(body.encode("utf-8", "surrogatepass")):
                    out.append(self.words.part(ids))
                return out, text[end + len(body) :]
        out += map(self.words.__getitem__, found)
        return out, text[end:]


class Decoder:
    """Bytes of ids to text, as they come: a character split over tokens waits for its last byte, and bytes that no
    text has become U+FFFD."""

    def __init__(self, vocabulary: Vocabulary):
        self.vocabulary, self.machine = vocabulary, codecs.getincrementaldecoder("utf-8")("replace")

    def feed(self, ids: list[int]) -> str:
        return self.feed_bytes(b"".join([self.vocabulary.token_bytes.get(i, b"") for i in ids]))

    def feed_bytes(self, data: bytes) -> str:
        return self.machine.decode(data)

    def finish(self) -> str:
        return self.machine.decode(b"", True)


_loaded: dict[bytes, Vocabulary] = {}


def load(raw: bytes) -> Vocabulary:
    """One vocabulary a worker for each file content."""
    key = hashlib.sha256(raw).digest()
    if key not in _loaded:
        _loaded[key] = Vocabulary(raw)
    return _loaded[key]


def chunks(data: memoryview | None) -> Iterator[tuple[str, bool]]:
    """The text in pieces, and whether each is the last; there is always one. No piece ends within a character."""
    machine, size = codecs.getincrementaldecoder("utf-8")("replace"), len(data) if data is not None else 0
    for at in range(0, max(size, 1), CHUNK):
        last = at + CHUNK >= size
        yield machine.decode(bytes(data[at : at + CHUNK]) if size else b"", last), last


def streamed(data: memoryview | None, words: Words) -> Iterator[list[Part]]:
    """The parts of a text, list by list."""
    stream = TextStream(words)
    for piece, last in chunks(data):
        yield stream.feed(piece, last)


class RoundTrip:
    """Takes parts as they come: number and digest of the ids, digest of the text decoded from them."""

    def __init__(self, vocabulary: Vocabulary):
        self.count, self.ids, self.text, self.decoder = 0, hashlib.sha256(), hashlib.sha256(), Decoder(vocabulary)

    def feed(self, parts: list[Part]) -> None:
        if parts:
            self.ids.update((b"," if self.count else b"") + ",".join([p[0] for p in parts]).encode())
            self.count += sum([p[1] for p in parts])
            self.text.update(self.decoder.feed_bytes(b"".join([p[2] for p in parts])).encode("utf-8"))

    def finish(self) -> tuple[int, str, str]:
        self.text.update(self.decoder.finish().encode("utf-8"))
        return self.count, self.ids.hexdigest(), self.text.hexdigest()


def _views(column: pa.Array) -> Iterator[memoryview | None]:
    """The UTF-8 bytes of each text where they lie."""
    for x in column.cast(pa.binary()):
        yield memoryview(x.as_buffer()) if x.is_valid else None


def encode_column(df: DataFrame, raw: bytes, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns, ``ids`` array<int> and ``decoded`` string of every text; raw: content of the vocabulary file."""
    shared = df.sparkSession.sparkContext.broadcast(raw)  # one vocabulary file, some 2 MB whatever the data
    schema = with_fields(df, keep, "ids array<int>, decoded string")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = load(shared.value)
        words = Words(v)
        for batch in slices(batches, text):
            ids, texts = [], []
            for data in _views(batch.column(text)):
                own, decoder = [], Decoder(v)
                back = []
                for parts in streamed(data, words):
                    new = [int(i) for p in parts for i in p[0].split(",")]
                    own += new
                    back.append(decoder.feed(new))
                ids.append(own)
                texts.append("".join([*back, decoder.finish()]))
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keep), pa.array(ids, pa.list_(pa.int32())), pa.array(texts, pa.string())], [*keep, "ids", "decoded"])

    return arrow_map(df.select(*keep, text), run, schema)


def token_digest(df: DataFrame, raw: bytes) -> DataFrame:
    """Number and digest of each text's ids, and the digest of the text decoded from them."""
    shared = df.sparkSession.sparkContext.broadcast(raw)  # one vocabulary file, some 2 MB whatever the data

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words(load(shared.value))
        for batch in slices(batches):
            rows = []
            for data in _views(batch.column("text")):
                trip = RoundTrip(words.vocabulary)
                for parts in streamed(data, words):
                    trip.feed(parts)
                rows.append(trip.finish())
            counts, ids, back = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(counts, pa.int64()), pa.array(ids), pa.array(back)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    docs = df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return arrow_map(docs, run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op6_bpe_roundtrip(spark: SparkSession, sf_dir: str, vocabulary: str | None = None) -> DataFrame:
    if vocabulary is None:
        import public_tokenizers

        vocabulary = public_tokenizers.path("byte_bpe_50k.json")
    with open(vocabulary, "rb") as f:
        return token_digest(read(spark, sf_dir, "documents"), f.read())
