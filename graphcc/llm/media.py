"""Media columns: lossless PNG in binary columns, and low-frequency cosine-transform hashes.

A payload is stored as an 8-bit grey image, 64 samples wide. The writer picks the
best of the None, Sub and Up filters for an image; the reader checks the signature
and every chunk's CRC, inflates IDAT and undoes all five filters with numpy. The
hash reads the decoded samples: box-averaged to 32 x 32, cosine-transformed, and
the 8 x 8 lowest frequencies compared with their median.

Null text counts as empty; empty text gives 64 zero bytes. Null doc_id and repeated
rows are kept, extra columns ignored; equal texts give equal values. A very long text takes a few
times its own size in memory while it is written or read.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

WIDTH = 64
#: Fixed value: the eight bytes that every PNG file begins with.
SIGNATURE = bytes([137, 80, 78, 71, 13, 10, 26, 10])
SIDE, LOW = 32, 8
#: Rows of an image that are averaged at a time.
BLOCK = 1024
_k, _x = np.arange(LOW)[:, None], np.arange(SIDE)[None, :]
_DCT = np.cos(np.pi * (2 * _x + 1) * _k / (2 * SIDE))


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def encode_png(payload: bytes, width: int = WIDTH, level: int = 3) -> bytes:
    """A grey image of ``width`` columns; the payload's length is a multiple of it."""
    img = np.frombuffer(payload, np.uint8).reshape(-1, width)
    sub, up = img.copy(), img.copy()
    sub[:, 1:] -= img[:, :-1]
    up[1:] -= img[:-1]
    cost = [np.minimum(x, -x).sum(dtype=np.int64) for x in (img, sub, up)]  # -x: 256 - x
    kind = int(np.argmin(cost))
    lines = np.empty((len(img), width + 1), np.uint8)
    lines[:, 0] = kind
    lines[:, 1:] = (img, sub, up)[kind]
    head = struct.pack(">IIBBBBB", width, len(img), 8, 0, 0, 0, 0)
    return SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(lines.tobytes(), level)) + _chunk(b"IEND", b"")


def _diagonals(kind: np.ndarray, rows: np.ndarray, above: np.ndarray) -> np.ndarray:
    """Rows of the Average (3) and Paeth (4) filters undone: what lies on one diagonal depends on earlier diagonals only."""
    height, width = rows.shape
    out = np.zeros((height + 1, width + 1), np.int16)  # with the row above, and a column of zeros on the left
    out[0, 1:] = above
    average = kind == 3
    for d in range(height + width - 1):
        i = np.arange(max(0, d - width + 1), min(height, d + 1))
        j = d - i
        left, up, corner = out[i + 1, j], out[i, j + 1], out[i, j]
        p = left + up - corner
        a, b, c = np.abs(p - left), np.abs(p - up), np.abs(p - corner)
        paeth = np.where((a <= b) & (a <= c), left, np.where(b <= c, up, corner))
        out[i + 1, j + 1] = rows[i, j] + np.where(average[i], (left + up) // 2, paeth) & 255
    return out[1:, 1:].astype(np.uint8)


def _unfilter(kinds: np.ndarray, rows: np.ndarray) -> np.ndarray:
    if len(kinds) and kinds.max() > 4:
        raise ValueError(f"unknown PNG filter {kinds.max()}")
    out = np.empty_like(rows)
    group = np.where(kinds >= 3, 3, kinds)
    cuts = [0, *(np.flatnonzero(group[1:] != group[:-1]) + 1).tolist(), len(kinds)]
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        above = out[a - 1] if a else np.zeros(rows.shape[1], np.uint8)
        if group[a] == 0:
            out[a:b] = rows[a:b]
        elif group[a] == 1:
            np.cumsum(rows[a:b], axis=1, dtype=np.uint8, out=out[a:b])
        elif group[a] == 2:
            np.cumsum(rows[a:b], axis=0, dtype=np.uint8, out=out[a:b])
            out[a:b] += above
        else:
            out[a:b] = _diagonals(kinds[a:b], rows[a:b], above)
    return out


def decode_png(data: bytes) -> np.ndarray:
    """Samples of an 8-bit grey PNG; raises ValueError if a checksum or the layout is wrong."""
    if data[:8] != SIGNATURE:
        raise ValueError("not a PNG")
    at, packed, shape = 8, [], None
    while at + 12 <= len(data):
        (n,) = struct.unpack_from(">I", data, at)
        kind, body = data[at + 4 : at + 8], data[at + 8 : at + 8 + n]
        if len(data) < at + 12 + n or struct.unpack_from(">I", data, at + 8 + n)[0] != zlib.crc32(kind + body):
            raise ValueError(f"bad checksum in {kind!r}")
        at += 12 + n
        if kind == b"IHDR":
            width, height, *form = struct.unpack(">IIBBBBB", body)
            if form != [8, 0, 0, 0, 0]:
                raise ValueError("only 8-bit grey without interlace")
            shape = height, width
        elif kind == b"IDAT":
            packed.append(body)
        elif kind == b"IEND":
            if shape is None:
                break
            lines = np.frombuffer(zlib.decompress(b"".join(packed)), np.uint8).reshape(shape[0], shape[1] + 1)
            return _unfilter(lines[:, 0], lines[:, 1:])
    raise ValueError("cut short")


def _overlaps(first: int, rows: int, total: int) -> np.ndarray:
    """How much of each of ``rows`` rows from ``first`` on lies in each of ``SIDE`` equal stretches of ``total`` rows."""
    edge = np.arange(SIDE + 1) * (total / SIDE)
    row = np.arange(first, first + rows)
    return np.maximum(np.minimum(row + 1, edge[1:, None]) - np.maximum(row, edge[:-1, None]), 0)


def _shrink(x: np.ndarray) -> np.ndarray:
    """``SIDE`` means over equal stretches of rows; a row that two stretches share counts in both by its parts."""
    out = np.zeros((SIDE, x.shape[1]))
    for a in range(0, len(x), BLOCK):
        part = x[a : a + BLOCK].astype(np.float64)
        out += _overlaps(a, len(part), len(x)) @ part
    return out * (SIDE / len(x))


def cosine_hash(img: np.ndarray) -> bytes:
    """64 bits: which of the lowest 8 x 8 cosine coefficients lie above their median. Works in memory of a fixed size."""
    small = _shrink(_shrink(img).T).T
    low = np.round(_DCT @ small @ _DCT.T, 4).ravel()
    return np.packbits(low > np.median(low[1:])).tobytes()


def payload_of(text: str | None, width: int = WIDTH) -> tuple[bytes, int]:
    raw = (text or "").encode()
    return raw + bytes(-len(raw) % width if raw else width), len(raw)


SCHEMA = "doc_id long, n_bytes long, media binary, cosine_hash binary"
FEATURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows: list[tuple] = []
        held = 0
        for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            payload, n = payload_of(text.as_py())
            media = encode_png(payload)
            rows.append((doc, n, media))
            held += len(media)
            if held > 8 << 20:
                yield _media_rows(rows)
                rows, held = [], 0
        if rows:
            yield _media_rows(rows)


def _media_rows(rows: list[tuple]) -> pa.RecordBatch:
    doc, n, media = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(n, pa.int64()), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for doc, n, media in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
            stored = media.as_py()
            img = decode_png(stored)
            payload = img.tobytes()
            rows.append((doc, n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), cosine_hash(img).hex()))
        if rows:
            kinds = [pa.int64()] * 3 + [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows, strict=True), kinds, strict=True)], [c.split()[0] for c in FEATURES.split(", ")])


def encode_texts(docs: DataFrame) -> DataFrame:
    """``(doc_id, n_bytes, media)``: each whole text as PNG in a binary column."""
    return docs.select("doc_id", "text").mapInArrow(_encode, "doc_id long, n_bytes long, media binary")


def media_features(media: DataFrame) -> DataFrame:
    """Digests and hash of ``(doc_id, n_bytes, media)``, from the samples read back out of the stored form."""
    return media.select("doc_id", "n_bytes", "media").mapInArrow(_features, FEATURES)
