"""Media columns: bytes stored as 8-bit grey PNG, read back with checks, and cosine-transform hashes."""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from nearcopy.llm.common import arrow_map, batch, check_columns, claim, documents

#: Fixed values of the PNG format.
SIGNATURE = b"\x89PNG\r\n\x1a\n"
NONE, SUB, UP, AVERAGE, PAETH = range(5)

WIDTH = 64
_SIDE, _LOW = 32, 8
_COSINE = np.cos(np.pi * (2 * np.arange(_SIDE)[None, :] + 1) * np.arange(_LOW)[:, None] / (2 * _SIDE))


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def filter_rows(pixels: np.ndarray, kind: int) -> np.ndarray:
    """Rows of 8-bit samples filtered by one of the five kinds."""
    left, up, corner = np.zeros_like(pixels), np.zeros_like(pixels), np.zeros_like(pixels)
    left[:, 1:], up[1:], corner[1:, 1:] = pixels[:, :-1], pixels[:-1], pixels[:-1, :-1]
    if kind == NONE:
        return pixels
    if kind == SUB:
        return pixels - left
    if kind == UP:
        return pixels - up
    if kind == AVERAGE:
        return pixels - ((left.astype(np.uint16) + up) >> 1).astype(np.uint8)
    return pixels - _paeth(left.astype(np.int16), up.astype(np.int16), corner.astype(np.int16)).astype(np.uint8)


def _paeth(a, b, c):
    p = a + b - c
    da, db, dc = abs(p - a), abs(p - b), abs(p - c)
    return np.where((da <= db) & (da <= dc), a, np.where(db <= dc, b, c))


def unfilter_rows(kinds: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Undo filter_rows; `kinds` has the filter of each row. Runs of rows with one kind go together."""
    out = np.empty_like(rows)
    height = len(rows)
    cuts = np.flatnonzero(np.diff(kinds)) + 1
    zero = np.zeros(rows.shape[1], np.uint8)
    for a, b in zip([0, *cuts], [*cuts, height], strict=True):
        if a == b:
            continue
        kind, above = int(kinds[a]), out[a - 1] if a else zero
        if kind == NONE:
            out[a:b] = rows[a:b]
        elif kind == SUB:
            np.cumsum(rows[a:b], axis=1, dtype=np.uint8, out=out[a:b])
        elif kind == UP:
            np.cumsum(rows[a:b], axis=0, dtype=np.uint8, out=out[a:b])
            out[a:b] += above
        elif kind in (AVERAGE, PAETH):
            out[a:b] = _unfilter_diagonals(rows[a:b], above, kind)
        else:
            raise ValueError(f"there is no filter {kind}")
    return out


def _unfilter_diagonals(rows: np.ndarray, above: np.ndarray, kind: int) -> np.ndarray:
    """Rows of one kind whose samples depend on the left, upper and corner one: all samples of an anti-diagonal at a
    time."""
    height, width = rows.shape
    done = np.zeros((height + 1, width + 1), np.int16)  # with the row above and an empty column at the left
    done[0, 1:] = above
    for s in range(height + width - 1):
        r = np.arange(max(0, s - width + 1), min(height - 1, s) + 1)
        c = s - r
        left, up = done[r + 1, c], done[r, c + 1]
        guess = (left + up) >> 1 if kind == AVERAGE else _paeth(left, up, done[r, c])
        done[r + 1, c + 1] = (rows[r, c] + guess) & 255
    return done[1:, 1:].astype(np.uint8)


def encode_png(payload: bytes, width: int = WIDTH, level: int = 1, chunk_bytes: int = 1 << 16) -> bytes:
    """payload: whole rows of `width` samples. The filter with the smallest sum of signed sizes is taken for all
    rows."""
    pixels = np.frombuffer(payload, np.uint8).reshape(-1, width)
    head = pixels[:256]
    cost = {k: int(np.abs(filter_rows(head, k).view(np.int8).astype(np.int16)).sum()) for k in (NONE, SUB, UP)}
    kind = min(cost, key=cost.get)
    rows = np.empty((len(pixels), width + 1), np.uint8)
    rows[:, 0], rows[:, 1:] = kind, filter_rows(pixels, kind)
    packed = zlib.compress(rows.tobytes(), level)
    body = b"".join(_chunk(b"IDAT", packed[i : i + chunk_bytes]) for i in range(0, len(packed), chunk_bytes))
    return SIGNATURE + _chunk(
        b"IHDR", struct.pack(">IIBBBBB", width, len(pixels), 8, 0, 0, 0, 0)
    ) + body + _chunk(b"IEND", b"")


def decode_png(data: bytes) -> np.ndarray:
    """Samples of an 8-bit grey PNG; ValueError for a wrong signature, length, checksum or form."""
    if data[:8] != SIGNATURE:
        raise ValueError("no PNG signature")
    at, size, packed, ended = 8, None, [], False
    while at < len(data) and not ended:
        if at + 12 > len(data):
            raise ValueError("cut off in a chunk")
        n, kind = struct.unpack(">I4s", data[at : at + 8])
        body = data[at + 8 : at + 8 + n]
        if len(body) < n or zlib.crc32(kind + body) != struct.unpack(">I", data[at + 8 + n : at + 12 + n])[0]:
            raise ValueError(f"checksum of chunk {kind!r}")
        at += 12 + n
        if kind == b"IHDR":
            size = struct.unpack(">IIBBBBB", body)
        elif kind == b"IDAT":
            packed.append(body)
        ended = kind == b"IEND"
    if not ended or size is None:
        raise ValueError("a header or end is missing")
    if size[2:] != (8, 0, 0, 0, 0):
        raise ValueError(f"only 8-bit grey without interlace is read, not {size[2:]}")
    try:
        raw = zlib.decompress(b"".join(packed))
    except zlib.error as e:
        raise ValueError(f"data: {e}") from None
    if len(raw) != size[1] * (size[0] + 1):
        raise ValueError("wrong number of samples")
    rows = np.frombuffer(raw, np.uint8).reshape(size[1], size[0] + 1)
    return unfilter_rows(rows[:, 0], rows[:, 1:])


def cosine_hash(pixels: np.ndarray) -> bytes:
    """64 bits: which of the 8 x 8 lowest frequencies (without the mean) of the 32 x 32 picture lie above their
    median."""

    def shrink(x):
        n = len(x)
        if n < _SIDE:
            return x[np.arange(_SIDE) * n // _SIDE]
        cuts = np.arange(_SIDE) * n // _SIDE
        return np.add.reduceat(x, cuts, axis=0) / np.diff([*cuts, n])[:, None]

    small = shrink(shrink(pixels.astype(np.float32)).T.astype(np.float64)).T
    low = np.round(_COSINE @ small @ _COSINE.T, 6).ravel()
    low[0] = np.median(low[1:])
    return np.packbits(low > low[0]).tobytes()


def add_media(docs: DataFrame, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """Per row: id_column, n_bytes, media (PNG), feature (8 bytes), and what was read back: payload.

    The text's UTF-8 bytes are filled with zero bytes to a positive multiple of 64 and stored row by row.
    A null text counts as empty: one row of zeros. Equal texts give equal media and features.
    """
    check_columns(docs, id_column, text)
    kind = docs.schema[id_column].dataType.simpleString()
    schema = f"`{id_column}` {kind}, n_bytes long, media binary, feature binary, payload binary"
    return docs.select(id_column, docs[text].alias("_text")).transform(arrow_map, _media(id_column, False), schema)


def _media(id_column, digests):
    def run(batches):
        claim("media")
        for b in batches:
            rows: list[tuple] = []
            ids = []
            for i, t in enumerate(b.column("_text")):
                raw = (t.as_py() or "").encode()
                media = encode_png(raw + bytes(-len(raw) % WIDTH if raw else WIDTH))
                pixels = decode_png(media)
                payload, feature = pixels.tobytes(), cosine_hash(pixels)
                ids.append(i)
                if digests:
                    read = (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
                    rows.append((len(raw), *read, len(media), hashlib.sha256(media).hexdigest(), feature.hex()))
                else:
                    rows.append((len(raw), media, feature, payload))
                if len(rows) >= 512 or i == b.num_rows - 1:
                    schema = pa.schema([b.schema.field(id_column), *(_DIGEST if digests else _MEDIA)])
                    yield batch(schema, b.column(id_column).take(pa.array(ids)), *map(list, zip(*rows, strict=True)))
                    rows, ids = [], []

    return run


_MEDIA = pa.schema(
    [("n_bytes", pa.int64()), ("media", pa.binary()), ("feature", pa.binary()), ("payload", pa.binary())]
)
_DIGEST = pa.schema(
    [
        *[("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string())],
        *[
            ("tail_crc32", pa.int64()),
            ("media_bytes", pa.int64()),
            ("media_sha256", pa.string()),
            ("feature", pa.string()),
        ],
    ]
)


def op4_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long"
    schema += ", media_sha256 string, feature string"
    return docs.select("doc_id", docs["text"].alias("_text")).transform(arrow_map, _media("doc_id", True), schema)
