"""TIFF media columns: pages are stored, found by walking image directories, and decoded to samples.

Read: either byte order, several directories, strips or tiles, no compression, PackBits, LZW and deflate, horizontal
prediction, 8- or 16-bit samples. Written: 8-bit grey pages of strips, deflated after horizontal prediction by default.
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

from worldfold.llm.common import documents

# Fixed values of the format: tags, field sizes, compression codes.
WIDTH, LENGTH, BITS, COMPRESSION, PHOTOMETRIC = 256, 257, 258, 259, 262
STRIP_OFFSETS, SAMPLES, ROWS_PER_STRIP, STRIP_COUNTS, PLANAR, PREDICTOR = 273, 277, 278, 279, 284, 317
TILE_WIDTH, TILE_LENGTH, TILE_OFFSETS, TILE_COUNTS = 322, 323, 324, 325
SIZES = {1: 1, 2: 1, 3: 2, 4: 4, 5: 8, 6: 1, 7: 1, 8: 2, 9: 4, 10: 8, 11: 4, 12: 8, 16: 8}
CODES = {1: "B", 3: "H", 4: "I", 16: "Q"}
NONE, LZW, DEFLATE, PACKBITS, OLD_DEFLATE = 1, 5, 8, 32773, 32946

ROW = 64
#: Rows of a page; longer payloads go on in further pages.
PAGE_ROWS, STRIP_ROWS = 1 << 16, 1024


#: The largest page that is read, and how many bytes a byte of a file can unpack to (that of LZW, the densest, with room).
PAGE_BYTES, MOST_OUT = 1 << 31, 4000


@dataclass
class Page:
    width: int
    height: int
    samples: np.ndarray  # height x width x channels


def packbits_decode(data: bytes) -> bytes:
    out, i = bytearray(), 0
    while i < len(data):
        n = data[i]
        i += 1
        if n < 128:
            out += data[i : i + n + 1]
            i += n + 1
        elif n > 128:
            out += data[i : i + 1] * (257 - n)
            i += 1
    return bytes(out)


def packbits_encode(data: bytes) -> bytes:
    out, i, n = bytearray(), 0, len(data)
    while i < n:
        j = i + 1
        while j < n and j - i < 128 and data[j] == data[i]:
            j += 1
        if j - i > 1:
            out += bytes([257 - (j - i), data[i]])
        else:
            while j < n and j - i < 128 and (j + 1 >= n or data[j] != data[j + 1]):
                j += 1
            out += bytes([j - i - 1]) + data[i:j]
        i = j
    return bytes(out)


def lzw_decode(data: bytes) -> bytes:
    """Codes come high bit first and grow one code early, as the format has it."""
    table = [bytes([i]) for i in range(256)] + [b"", b""]
    out, held, bits, width, last = [], 0, 0, 9, None
    for byte in data:
        held, bits = held << 8 | byte, bits + 8
        if bits < width:
            continue
        bits -= width
        code, held = held >> bits, held & ((1 << bits) - 1)
        if code == 257:
            break
        if code == 256:
            del table[258:]
            width, last = 9, None
            continue
        if last is None:
            entry = table[code]
        else:
            entry = table[code] if code < len(table) else last + last[:1]
            table.append(last + entry[:1])
        out.append(entry)
        last = entry
        if len(table) + 1 >= 1 << width and width < 12:
            width += 1
    return b"".join(out)


def lzw_encode(data: bytes) -> bytes:
    out, held, bits, width = bytearray(), 0, 0, 9

    def put(code: int) -> None:
        nonlocal held, bits
        held, bits = held << width | code, bits + width
        while bits >= 8:
            bits -= 8
            out.append(held >> bits)
            held &= (1 << bits) - 1

    table = {bytes([i]): i for i in range(256)}
    put(256)
    at = b""
    size = 258
    for i in range(len(data)):
        more = at + data[i : i + 1]
        if more in table:
            at = more
            continue
        put(table[at])
        table[more] = size
        size += 1
        if size == 4095:
            put(256)
            table = {bytes([j]): j for j in range(256)}
            size, width = 258, 9
        elif size == 1 << width:
            width += 1
        at = data[i : i + 1]
    if at:
        put(table[at])
        size += 1
        if size == 1 << width and width < 12:
            width += 1
    put(257)
    if bits:
        out.append(held << (8 - bits) & 255)
    return bytes(out)


def _inflate(data: bytes, kind: int) -> bytes:
    if kind == NONE:
        return data
    if kind == PACKBITS:
        return packbits_decode(data)
    if kind == LZW:
        return lzw_decode(data)
    if kind in (DEFLATE, OLD_DEFLATE):
        return zlib.decompress(data)
    raise ValueError(f"compression {kind} is not supported")


def _deflate(data: bytes, kind: int) -> bytes:
    return {NONE: lambda: data, PACKBITS: lambda: packbits_encode(data), LZW: lambda: lzw_encode(data), DEFLATE: lambda: zlib.compress(data, 1)}[kind]()


def directories(file: bytes) -> Iterator[dict[int, list[int]]]:
    """Tags of each image directory, in the order of the chain; a chain that turns back on itself is refused."""
    order = {b"II": "<", b"MM": ">"}.get(file[:2])
    if order is None or struct.unpack_from(order + "H", file, 2)[0] != 42:
        raise ValueError("not a TIFF file")
    at, seen = struct.unpack_from(order + "I", file, 4)[0], set()
    while at:
        if at in seen:
            raise ValueError("image directories form a loop")
        seen.add(at)
        n = struct.unpack_from(order + "H", file, at)[0]
        tags: dict[int, list[int]] = {}
        for k in range(n):
            tag, kind, count = struct.unpack_from(order + "HHI", file, at + 2 + 12 * k)
            size = SIZES.get(kind, 1) * count
            where = at + 10 + 12 * k if size <= 4 else struct.unpack_from(order + "I", file, at + 10 + 12 * k)[0]
            if kind in CODES:
                tags[tag] = list(struct.unpack_from(f"{order}{count}{CODES[kind]}", file, where))
        tags[-1] = [order == ">"]
        yield tags
        at = struct.unpack_from(order + "I", file, at + 2 + 12 * n)[0]


def decode(file: bytes) -> list[Page]:
    """All pages of a file, prediction undone."""
    pages = []
    for t in directories(file):
        width, height = t[WIDTH][0], t[LENGTH][0]
        channels, bits = t.get(SAMPLES, [1])[0], t.get(BITS, [1])[0]
        if bits not in (8, 16) or t.get(PLANAR, [1])[0] != 1:
            raise ValueError("only whole 8- or 16-bit samples side by side are supported")
        kind = np.dtype(np.uint8) if bits == 8 else np.dtype(">u2" if t[-1][0] else "<u2")
        tiled = TILE_OFFSETS in t
        w, h = (t[TILE_WIDTH][0], t[TILE_LENGTH][0]) if tiled else (width, min(height, t.get(ROWS_PER_STRIP, [height])[0]))
        size = height * width * channels * kind.itemsize
        if size > PAGE_BYTES or size > len(file) * MOST_OUT:
            raise ValueError(f"a page of {width} x {height} x {channels} is more than its file can hold")
        out = np.zeros((height, width, channels), kind.newbyteorder("="))
        across = -(-width // w)
        for i, (o, n) in enumerate(zip(t[TILE_OFFSETS if tiled else STRIP_OFFSETS], t[TILE_COUNTS if tiled else STRIP_COUNTS], strict=True)):
            y, x = i // across * h, i % across * w
            rows = h if tiled else min(h, height - y)
            part = np.frombuffer(_inflate(file[o : o + n], t.get(COMPRESSION, [1])[0]), kind, rows * w * channels).reshape(rows, w, channels).astype(out.dtype)
            if t.get(PREDICTOR, [1])[0] == 2:
                part = np.cumsum(part, axis=1, dtype=out.dtype)
            out[y : y + rows, x : x + w] = part[: height - y, : width - x]
        pages.append(Page(width, height, out))
    return pages


def encode(pages: list[np.ndarray], compression: int = DEFLATE, predictor: int = 2, tile: int | None = None, order: str = "<", strip_rows: int = STRIP_ROWS) -> bytes:
    """Grey 8-bit pages (height x width) as one file of strips, or of square tiles with a side of ``tile``."""
    out = bytearray((b"II" if order == "<" else b"MM") + struct.pack(order + "HI", 42, 0))
    link = 4
    for p in pages:
        height, width = p.shape
        if tile:
            parts = [np.pad(p[y : y + tile, x : x + tile], ((0, max(0, y + tile - height)), (0, max(0, x + tile - width)))) for y in range(0, height, tile) for x in range(0, width, tile)]
        else:
            parts = [p[y : y + strip_rows] for y in range(0, height, strip_rows)]
        offsets, counts = [], []
        for part in parts:
            if predictor == 2:
                first = part[:, :1]
                part = np.concatenate((first, part[:, 1:] - part[:, :-1]), axis=1)
            raw = _deflate(np.ascontiguousarray(part).tobytes(), compression)
            offsets.append(len(out))
            counts.append(len(raw))
            out += raw
        place = (TILE_OFFSETS, TILE_COUNTS) if tile else (STRIP_OFFSETS, STRIP_COUNTS)
        tags = [(WIDTH, 4, [width]), (LENGTH, 4, [height]), (BITS, 3, [8]), (COMPRESSION, 3, [compression]), (PHOTOMETRIC, 3, [1]), (place[0], 4, offsets), (SAMPLES, 3, [1]), (place[1], 4, counts), (PREDICTOR, 3, [predictor])]
        tags += [(TILE_WIDTH, 4, [tile]), (TILE_LENGTH, 4, [tile])] if tile else [(ROWS_PER_STRIP, 4, [strip_rows])]
        fields = b""
        for tag, kind, values in sorted(tags):
            raw = struct.pack(f"{order}{len(values)}{CODES[kind]}", *values)
            if len(raw) > 4:
                out += b"\0" * (len(out) % 2)
                at = len(out)
                out += raw
                raw = struct.pack(order + "I", at)
            fields += struct.pack(order + "HHI", tag, kind, len(values)) + raw.ljust(4, b"\0")
        out += b"\0" * (len(out) % 2)
        struct.pack_into(order + "I", out, link, len(out))
        out += struct.pack(order + "H", len(tags)) + fields
        link = len(out)
        out += struct.pack(order + "I", 0)
    return bytes(out)


def store(text: str, compression: int = DEFLATE, predictor: int = 2) -> tuple[bytes, int]:
    """A text's file and its unpadded bytes: rows of 64 samples, zeros to the end of the last row, one row at least."""
    raw = text.encode()
    padded = raw + b"\0" * (-len(raw) % ROW if raw else ROW)
    rows = np.frombuffer(padded, np.uint8).reshape(-1, ROW)
    return encode([rows[i : i + PAGE_ROWS] for i in range(0, len(rows), PAGE_ROWS)], compression, predictor), len(raw)


def feature(payload: np.ndarray) -> str:
    """Mean, deviation and an 8-bin histogram of all samples, and an 8 x 8 mean hash of the page's shape."""
    counts = np.bincount(payload, minlength=256)
    n, values = len(payload), np.arange(256)
    mean = float((counts * values).sum() / n)
    dev = float(np.sqrt(max(0.0, (counts * values * values).sum() / n - mean * mean)))
    share = (counts.reshape(8, 32).sum(1) * 255 // n).astype(np.uint8).tobytes().hex()
    rows = payload.reshape(-1, ROW)
    edges = np.linspace(0, len(rows), 9).astype(int)
    sums = np.concatenate((np.zeros((1, 8), np.int64), np.cumsum(rows.reshape(len(rows), 8, 8).sum(2, dtype=np.int64), axis=0)))
    cells = (sums[edges[1:]] - sums[edges[:-1]]) / np.maximum(1, edges[1:] - edges[:-1])[:, None] / 8
    return f"{mean:.3f}:{dev:.3f}:{share}:{np.packbits((cells > mean).ravel()).tobytes().hex()}"


def stored(docs: DataFrame, key: str = "doc_id", text: str = "text", compression: int = DEFLATE, predictor: int = 2) -> DataFrame:
    """key, n_bytes, media: each text as a TIFF file. Null text is empty: one row of zeros."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k, t in zip(b.column(0), b.column(1), strict=True):  # a row a batch bounds what a long text takes
                file, n = store(t.as_py() or "", compression, predictor)
                yield pa.RecordBatch.from_arrays([pa.array([k.as_py()], b.schema.types[0]), pa.array([n], pa.int64()), pa.array([file], pa.binary())], [key, "n_bytes", "media"])

    schema = docs.select(key).schema.add("n_bytes", "long").add("media", "binary")
    return docs.select(key, text).mapInArrow(run, schema)


def pages(files: DataFrame, key: str = "doc_id", media: str = "media") -> DataFrame:
    """A row a page: key, page (from 0), width, height, channels, samples (bytes, row by row), error.

    A file that is broken, of a kind that is not read, or with a page over PAGE_BYTES or larger than its data can unpack to gives one row with the error's text; null gives no row.
    """
    schema = files.select(key).schema.add("page", "integer").add("width", "integer").add("height", "integer").add("channels", "integer").add("samples", "binary").add("error", "string")
    names = [f.name for f in schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k, m in zip(b.column(0), b.column(1), strict=True):
                file = m.as_py()
                if file is None:
                    continue
                try:
                    rows = [(i, p.width, p.height, p.samples.shape[2], p.samples.tobytes(), None) for i, p in enumerate(decode(file))]
                except (ValueError, KeyError, struct.error, zlib.error, IndexError, MemoryError, OverflowError) as e:
                    rows = [(None, None, None, None, None, str(e) or type(e).__name__)]
                for r in rows:
                    kinds = [b.schema.types[0], pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.string()]
                    yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip([k.as_py(), *r], kinds, strict=True)], names)

    return files.select(key, media).mapInArrow(run, schema)


def digests(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """A row a document: what is stored, read back page by page, and features of it.

    Null text is empty. Repeated rows are rows of their own; equal texts have equal values. An empty table gives no rows.
    """
    schema = f"{key} long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    names = [c.split()[0] for c in schema.split(", ")]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for k, t in zip(b.column(0), b.column(1), strict=True):
                file, n = store(t.as_py() or "")
                payload = np.concatenate([p.samples.ravel() for p in decode(file)])
                raw = payload.tobytes()
                rows.append((k.as_py(), n, len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-ROW:]), len(file), hashlib.sha256(file).hexdigest(), feature(payload)))
            cols = list(zip(*rows, strict=True)) or [()] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names)

    return docs.select(F.col(key).cast("long").alias(key), F.col(text).alias("text")).mapInArrow(run, schema)


def op8_tiff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(documents(spark, sf_dir))
