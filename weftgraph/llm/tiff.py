"""TIFF columns: write byte payloads as TIFF files, walk their directories and decode every page.

Reader: both byte orders, any number of directories, strips and tiles, no compression, PackBits, LZW
(most significant bit first) and deflate, horizontal predictor for 8- and 16-bit samples, chunky and planar
samples. A file that breaks the format gives one row with ``error`` set and no pixels; null or empty content
gives no row. One row per page.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, crc32, read, slices, text_blobs, with_fields

# Fixed values of the TIFF 6.0 format: tags, field sizes, compression codes.
WIDTH, LENGTH, BITS, COMPRESSION, PHOTOMETRIC = 256, 257, 258, 259, 262
STRIP_OFFSETS, SAMPLES, ROWS_PER_STRIP, STRIP_COUNTS, PLANAR, PREDICTOR = 273, 277, 278, 279, 284, 317
TILE_WIDTH, TILE_LENGTH, TILE_OFFSETS, TILE_COUNTS = 322, 323, 324, 325
FIELD_BYTES = {1: 1, 2: 1, 3: 2, 4: 4, 5: 8, 6: 1, 7: 1, 8: 2, 9: 4, 10: 8, 11: 4, 12: 8, 13: 4}
NONE, LZW, DEFLATE, PACKBITS, OLD_DEFLATE = 1, 5, 8, 32773, 32946
LZW_CLEAR, LZW_END = 256, 257

#: A payload row is 576 samples wide; a page holds at most this many rows.
ROW_BYTES, PAGE_ROWS, STRIP_ROWS, TILE = 576, 1024, 256, (192, 64)

PAGE_SCHEMA = "page int, width int, height int, samples int, bits int, compression int, predictor int, layout string, pixels binary, error string"


class TiffError(ValueError):
    """The bytes do not follow the format."""


@dataclass
class Page:
    index: int
    width: int
    height: int
    samples: int
    bits: int
    compression: int
    predictor: int
    layout: str
    pixels: bytes


def unpack_bits(data: bytes) -> bytes:
    out, i, n = [], 0, len(data)
    while i < n:
        head = data[i]
        if head < 128:
            out.append(data[i + 1 : i + 2 + head])
            i += head + 2
        else:
            if head > 128 and i + 1 < n:
                out.append(data[i + 1 : i + 2] * (257 - head))
            i += 1 if head == 128 else 2
    return b"".join(out)


def pack_bits(data: bytes) -> bytes:
    """Runs of three equal bytes or more become repeats, the rest literals of up to 128 bytes."""
    a = np.frombuffer(data, np.uint8)
    if not len(a):
        return b""
    starts = np.concatenate(([0], np.flatnonzero(a[1:] != a[:-1]) + 1))
    lengths = np.diff(np.concatenate((starts, [len(a)])))
    out, literal = [], 0

    def flush(stop: int) -> None:
        for at in range(literal, stop, 128):
            piece = data[at : min(at + 128, stop)]
            out.append(bytes([len(piece) - 1]) + piece)

    for at, length in zip(starts[lengths >= 3].tolist(), lengths[lengths >= 3].tolist(), strict=True):
        flush(at)
        literal = at + length
        for done in range(0, length, 128):
            piece = min(128, length - done)
            out.append(bytes([(257 - piece) & 255 if piece > 1 else 0, data[at]]))
    flush(len(data))
    return b"".join(out)


def unlzw(data: bytes) -> bytes:
    base = [bytes([i]) for i in range(256)] + [b"", b""]
    table, width, last, out = list(base), 9, None, []
    hold = bits = 0
    for byte in data:
        hold, bits = (hold << 8) | byte, bits + 8
        if bits < width:
            continue
        bits -= width
        code, hold = hold >> bits, hold & ((1 << bits) - 1)
        if code == LZW_END:
            break
        if code == LZW_CLEAR:
            table, width, last = list(base), 9, None
            continue
        if code < len(table):
            entry = table[code]
        elif code == len(table) and last:
            entry = last + last[:1]
        else:
            raise TiffError("LZW code out of range")
        out.append(entry)
        if last is not None:
            table.append(last + entry[:1])
        last = entry
        width = 12 if len(table) >= 2047 else max(9, (len(table) + 1).bit_length())
    return b"".join(out)


def lzw(data: bytes) -> bytes:
    codes: dict[bytes, int] = {}
    out, hold, bits, width, top = bytearray(), 0, 0, 9, 258

    def put(code: int) -> None:
        nonlocal hold, bits
        hold, bits = (hold << width) | code, bits + width
        while bits >= 8:
            bits -= 8
            out.append(hold >> bits & 255)
            hold &= (1 << bits) - 1

    put(LZW_CLEAR)
    word = b""
    for i in range(len(data)):
        longer = word + data[i : i + 1]
        if len(longer) == 1 or longer in codes:
            word = longer
            continue
        put(codes[word] if len(word) > 1 else word[0])
        codes[longer], top = top, top + 1
        width = min(12, max(9, top.bit_length()))
        word = data[i : i + 1]
        if top == 4094:
            put(LZW_CLEAR)
            codes, width, top = {}, 9, 258
    if word:
        put(codes[word] if len(word) > 1 else word[0])
        top += 1
        width = min(12, max(9, top.bit_length()))
    put(LZW_END)
    if bits:
        out.append(hold << (8 - bits) & 255)
    return bytes(out)


ENCODERS = {NONE: bytes, LZW: lzw, DEFLATE: lambda b: zlib.compress(b, 1), OLD_DEFLATE: lambda b: zlib.compress(b, 1), PACKBITS: pack_bits}
DECODERS = {NONE: bytes, LZW: unlzw, DEFLATE: zlib.decompress, OLD_DEFLATE: zlib.decompress, PACKBITS: unpack_bits}


def _difference(rows: np.ndarray) -> np.ndarray:
    """rows: (height, width, samples). Each sample minus the one to its left, modulo its range."""
    out = rows.copy()
    out[:, 1:] -= rows[:, :-1]
    return out


def encode(payload: bytes, pages: list[tuple[int, int, str]] | None = None) -> bytes:
    """A little-endian grey 8-bit TIFF of ``payload``, whose length is a positive multiple of ROW_BYTES.

    pages: compression, predictor and layout ("strip" or "tile") that pages take in turn.
    """
    if not payload or len(payload) % ROW_BYTES:
        raise ValueError(f"payload must be a positive multiple of {ROW_BYTES} bytes")
    pages = pages or [(DEFLATE, 2, "strip"), (PACKBITS, 1, "tile")]
    image = np.frombuffer(payload, np.uint8).reshape(-1, ROW_BYTES, 1)
    parts, at, link = [b"II*\0"], 8, 4
    links: list[tuple[int, int]] = []
    for number, top in enumerate(range(0, len(image), PAGE_ROWS)):
        rows = image[top : top + PAGE_ROWS]
        compression, predictor, layout = pages[number % len(pages)]
        if layout == "tile":
            tw, th = TILE
            full = np.pad(rows, ((0, -len(rows) % th), (0, -ROW_BYTES % tw), (0, 0)))
            blocks = [full[y : y + th, x : x + tw] for y in range(0, full.shape[0], th) for x in range(0, full.shape[1], tw)]
        else:
            blocks = [rows[y : y + STRIP_ROWS] for y in range(0, len(rows), STRIP_ROWS)]
        coded = [ENCODERS[compression]((_difference(b) if predictor == 2 else b).tobytes()) for b in blocks]
        body, offsets = [], []
        for c in coded:
            offsets.append(at)
            body.append(c + b"\0" * (len(c) % 2))
            at += len(body[-1])
        sizes = [len(c) for c in coded]
        tags = [(WIDTH, 4, [ROW_BYTES]), (LENGTH, 4, [len(rows)]), (BITS, 3, [8]), (COMPRESSION, 3, [compression]), (PHOTOMETRIC, 3, [1]), (SAMPLES, 3, [1]), (PREDICTOR, 3, [predictor])]
        tags += [(TILE_WIDTH, 4, [TILE[0]]), (TILE_LENGTH, 4, [TILE[1]]), (TILE_OFFSETS, 4, offsets), (TILE_COUNTS, 4, sizes)] if layout == "tile" else [(STRIP_OFFSETS, 4, offsets), (ROWS_PER_STRIP, 4, [STRIP_ROWS]), (STRIP_COUNTS, 4, sizes)]
        entries = []
        for tag, kind, values in sorted(tags):
            raw = struct.pack(f"<{len(values)}{'H' if kind == 3 else 'I'}", *values)
            if len(raw) > 4:
                body.append(raw)
                entries.append(struct.pack("<HHII", tag, kind, len(values), at))
                at += len(raw)
            else:
                entries.append(struct.pack("<HHI", tag, kind, len(values)) + raw.ljust(4, b"\0"))
        links.append((link, at))
        body.append(struct.pack("<H", len(entries)) + b"".join(entries) + b"\0\0\0\0")
        at += 2 + 12 * len(entries) + 4
        link = at - 4
        parts += body
    out = bytearray(parts[0] + b"\0\0\0\0" + b"".join(parts[1:]))
    for place, target in links:
        struct.pack_into("<I", out, place, target)
    return bytes(out)


def _directory(data: bytes, order: str, at: int) -> tuple[dict[int, list[int]], int]:
    (count,) = struct.unpack_from(order + "H", data, at)
    fields: dict[int, list[int]] = {}
    for k in range(count):
        tag, kind, n = struct.unpack_from(order + "HHI", data, at + 2 + 12 * k)
        if kind not in (1, 3, 4):
            continue
        size, place = FIELD_BYTES[kind] * n, at + 10 + 12 * k
        if size > 4:
            (place,) = struct.unpack_from(order + "I", data, place)
        fields[tag] = list(struct.unpack_from(f"{order}{n}{'B' if kind == 1 else 'H' if kind == 3 else 'I'}", data, place))
    return fields, struct.unpack_from(order + "I", data, at + 2 + 12 * count)[0]


def pages(data: bytes) -> Iterator[Page]:
    """Walk the directories and decode each page; TiffError where the bytes break the format."""
    try:
        yield from _pages(data)
    except TiffError:
        raise
    except (struct.error, zlib.error, ValueError, KeyError, IndexError, OverflowError, MemoryError) as e:
        raise TiffError(f"{type(e).__name__}: {e}") from e


def _pages(data: bytes) -> Iterator[Page]:
    order = {b"II*\0": "<", b"MM\0*": ">"}.get(data[:4])
    if order is None:
        raise TiffError("not a TIFF header")
    (at,) = struct.unpack_from(order + "I", data, 4)
    seen: set[int] = set()
    while at:
        if at in seen:
            raise TiffError("directories form a ring")
        seen.add(at)
        f, following = _directory(data, order, at)
        one = lambda tag, default: f.get(tag, [default])[0]  # noqa: B023, E731
        width, height, samples, planar = one(WIDTH, 0), one(LENGTH, 0), one(SAMPLES, 1), one(PLANAR, 1)
        bits, compression, predictor = one(BITS, 1), one(COMPRESSION, 1), one(PREDICTOR, 1)
        if bits not in (8, 16) or len(set(f.get(BITS, [bits]))) > 1 or compression not in DECODERS or predictor not in (1, 2) or not width or not height:
            raise TiffError(f"not supported: bits {bits}, compression {compression}, predictor {predictor}, {width} x {height}")
        layout = "tile" if TILE_OFFSETS in f else "strip"
        bw, bh = (f[TILE_WIDTH][0], f[TILE_LENGTH][0]) if layout == "tile" else (width, min(one(ROWS_PER_STRIP, height), height))
        offsets, sizes = (f[TILE_OFFSETS], f[TILE_COUNTS]) if layout == "tile" else (f[STRIP_OFFSETS], f[STRIP_COUNTS])
        dtype, per = np.dtype(np.uint8 if bits == 8 else order + "u2"), 1 if planar == 2 else samples
        image = np.zeros((height, width, samples), dtype)
        across, down = -(-width // bw), -(-height // bh)
        if len(offsets) < across * down * (samples if planar == 2 else 1):
            raise TiffError("fewer strips or tiles than the image needs")
        for k, (offset, size) in enumerate(zip(offsets, sizes, strict=True)):
            plane, cell = divmod(k, across * down)
            y, x = cell // across * bh, cell % across * bw
            rows = bh if layout == "tile" else min(bh, height - y)
            raw = DECODERS[compression](data[offset : offset + size])
            if len(raw) < rows * bw * per * dtype.itemsize:
                raise TiffError("a strip or tile is too short")
            block = np.frombuffer(raw, dtype, rows * bw * per).reshape(rows, bw, per)
            if predictor == 2:
                block = np.cumsum(block, axis=1, dtype=dtype.newbyteorder("="))
            target = image[y : y + rows, x : x + bw, plane : plane + 1] if planar == 2 else image[y : y + rows, x : x + bw]
            target[...] = block[: target.shape[0], : target.shape[1]]
        yield Page(len(seen) - 1, width, height, samples, bits, compression, predictor, layout, image.tobytes())
        at = following


def decode_column(df: DataFrame, content: str = "content", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """One row per page of the TIFF file in the binary column ``content``, with the ``keep`` columns.

    A file that cannot be read gives the pages before the fault, then one row whose ``error`` says why.
    """
    schema = with_fields(df, keep, PAGE_SCHEMA)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = {k: batch.column(k).to_pylist() for k in keep}
            for i, data in enumerate(batch.column(content).to_pylist()):
                if not data:
                    continue
                rows: list[tuple] = []
                try:
                    for p in pages(data):
                        rows.append((p.index, p.width, p.height, p.samples, p.bits, p.compression, p.predictor, p.layout, p.pixels, None))
                except TiffError as e:
                    rows.append((len(rows), *[None] * 8, str(e)))
                kinds = [pa.int32()] * 7 + [pa.string(), pa.binary(), pa.string()]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([own[k][i]] * len(rows), batch.column(k).type) for k in keep] + [pa.array([r[j] for r in rows], kinds[j]) for j in range(10)],
                    [*keep, "page", "width", "height", "samples", "bits", "compression", "predictor", "layout", "pixels", "error"],
                )

    return arrow_map(df.select(*keep, content), run, schema)


def payload_of(data: bytes) -> bytes:
    return data + b"\xff" * (-len(data) % ROW_BYTES or (0 if data else ROW_BYTES))


def encode_column(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The text column as TIFF files: ``keep`` and ``content``."""
    schema = with_fields(df, keep, "content binary")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text):
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(k) for k in keep), pa.array([encode(payload_of(b)) for b in text_blobs(batch, text)], pa.binary())], [*keep, "content"]
            )

    return arrow_map(df.select(*keep, text), run, schema)


def feature_of(found: list[Page]) -> str:
    """Page count and layouts, then mean, deviation, edge energy and a 16-bin histogram of all samples."""
    a = np.concatenate([np.frombuffer(p.pixels, np.uint8) for p in found])
    hist = np.bincount(a, minlength=256)
    grey = np.arange(256)
    mean = float((hist * grey).sum() / len(a))
    var = float((hist * (grey - mean) ** 2).sum() / len(a))
    edges = float(np.abs(np.diff(a.astype(np.int16))).mean())
    return f"{len(found)}p;{'+'.join(sorted({f'{p.layout}/{p.compression}/{p.predictor}' for p in found}))};{mean:.4f};{var:.4f};{edges:.4f};" + ",".join(map(str, hist.reshape(16, 16).sum(1)))


OUT = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "pages"]


def media_digest(df: DataFrame) -> DataFrame:
    """Store each text as TIFF, read the stored bytes back page by page, and digest what was read.

    Null text counts as empty; repeated rows give repeated rows; other columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            cols: list[list] = [[] for _ in range(8)]
            for data in text_blobs(batch):
                stored = encode(payload_of(data))
                found = list(pages(stored))
                back = b"".join(p.pixels for p in found)
                row = (len(data), len(back), hashlib.sha256(back).hexdigest(), crc32(back[-32:]), len(stored), hashlib.sha256(stored).hexdigest(), feature_of(found), len(found))
                for c, v in zip(cols, row, strict=True):
                    c.append(v)
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], OUT)

    return arrow_map(df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, pages int"
    )


def op1_tiff_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_digest(read(spark, sf_dir, "documents"))
