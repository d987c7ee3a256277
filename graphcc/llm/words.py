"""Vectorised words: boundaries and 64-bit hashes straight from Arrow string buffers.

A word is a maximal run of bytes other than 0x20 and 0x09-0x0D, so UTF-8 needs no
decoding. Hashes are polynomials over a random byte table modulo 2**64, finished
with an avalanche step; all temporaries are bounded by ``SLICE`` bytes of text.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLICE = 1 << 18
_U = np.uint64
_rng = np.random.default_rng(20240607)
BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * _U(2) + _U(1)
LOWER = BYTE.copy()
LOWER[65:91] = BYTE[97:123]
LANE = _rng.integers(1, 2**63, 64, dtype=np.uint64) * _U(2) + _U(1)
_BASE, SPACE = 0x9E3779B97F4A7C15 | 1, np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
#: 0 space, 1 letters, digits and all bytes of multi-byte characters, 2 other ASCII.
KIND = np.full(256, 2, np.uint8)
KIND[SPACE] = 0
KIND[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = 1
_powers: dict[str, np.ndarray] = {}


def mix(h: np.ndarray) -> np.ndarray:
    """Avalanche finaliser on uint64 (in a new array)."""
    h = h ^ (h >> _U(30))
    h *= _U(0xBF58476D1CE4E5B9)
    h ^= h >> _U(27)
    h *= _U(0x94D049BB133111EB)
    h ^= h >> _U(31)
    return h


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _powers or len(_powers["up"]) < n:
        size = max(n, SLICE + 4096)
        for name, base in (("up", _BASE), ("down", pow(_BASE, -1, 2**64))):
            t = np.full(size, base, np.uint64)
            t[0] = 1
            _powers[name] = np.cumprod(t)
    return _powers["up"], _powers["down"]


def _offsets(col: pa.Array) -> np.ndarray:
    """Row offsets of a string column into its data buffer, as they lie there."""
    kind = np.int64 if pa.types.is_large_string(col.type) else np.int32
    where = col.buffers()[1]
    return np.frombuffer(where, kind)[col.offset : col.offset + len(col) + 1] if where is not None else np.zeros(len(col) + 1, kind)


def text_buffer(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and its row offsets, nulls as empty."""
    if not (pa.types.is_string(col.type) or pa.types.is_large_string(col.type)):
        col = col.cast(pa.large_string())
    col = pc.fill_null(col, "") if col.null_count else col
    at, data = _offsets(col).astype(np.int64), col.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def slices(batch: pa.RecordBatch, column: str = "text", target: int | None = None) -> Iterator[pa.RecordBatch]:
    """Rows of a batch in runs of about ``target`` (``SLICE``) bytes of text, one row at least."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
    a, target = 0, target or SLICE
    while a < len(ends):
        b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + target, "right")))
        yield batch.slice(a, b - a)
        a = b


@dataclass
class Words:
    data: np.ndarray  # bytes of all rows
    starts: np.ndarray  # of each word, in data
    ends: np.ndarray
    at: np.ndarray  # row r has words at[r]:at[r+1]
    hashes: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.at)

    def rows(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.at) - 1), self.counts)


def words(col: pa.Array, lower: bool = False, by_kind: bool = False, hashed: bool = True) -> Words:
    """Words of every row; ``lower`` folds A-Z, ``by_kind`` also cuts between letters and other signs."""
    data, offs = text_buffer(col)
    n = len(data)
    if not n:
        z = np.zeros(0, np.int64)
        return Words(data, z, z, np.zeros(len(offs), np.int64), np.zeros(0, np.uint64))
    first = np.zeros(n + 1, bool)
    first[offs] = True
    if by_kind:
        kind = KIND[data]
        inside, step = kind > 0, kind[1:] != kind[:-1]
    else:
        inside = ~SPACE[data]
        step = inside[1:] != inside[:-1]
    first[1:-1] |= step
    first[0] = True
    first[n] = True
    starts = np.flatnonzero(inside & first[:-1])
    ends = np.flatnonzero(inside & first[1:]) + 1
    at = np.searchsorted(starts, offs)
    return Words(data, starts, ends, at, hashes(data, starts, ends, LOWER if lower else BYTE) if hashed else np.zeros(0, np.uint64))


def hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, table: np.ndarray = BYTE) -> np.ndarray:
    """Hash of each byte range, in blocks so that temporaries stay small."""
    out = np.empty(len(starts), np.uint64)
    i = 0
    while i < len(starts):
        j = max(i + 1, int(np.searchsorted(ends, starts[i] + SLICE, "right")))
        lo, hi = int(starts[i]), int(ends[j - 1])
        up, down = _tables(hi - lo + 1)
        c = np.zeros(hi - lo + 1, np.uint64)
        np.cumsum(table[data[lo:hi]] * up[: hi - lo], out=c[1:])
        s, e = starts[i:j] - lo, ends[i:j] - lo
        out[i:j] = mix((c[e] - c[s]) * down[s] + (e - s).astype(np.uint64))
        i = j
    return out


def grams(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of h[i:i+k] at each i up to len(h)-k."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = h[:n] * LANE[0]
    for j in range(1, k):
        out += h[j : n + j] * LANE[j % 64]
    return mix(out)


def rolling(h: np.ndarray, k: int) -> np.ndarray:
    """Like ``grams`` for long k, by prefix sums: constant work an element."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    up, down = _tables(len(h) + 1)
    c = np.zeros(len(h) + 1, np.uint64)
    np.cumsum(h * up[: len(h)], out=c[1:])
    return mix((c[k:] - c[:n]) * down[:n])


def shingle_sets(w: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct k-word shingle hashes of each row: all values, and row offsets.

    A row of 1 to k-1 words has its whole sequence as its one shingle.
    """
    all_grams = grams(w.hashes, k)
    parts, sizes = [], np.zeros(len(w.at) - 1, np.int64)
    for r, (a, b) in enumerate(zip(w.at[:-1].tolist(), w.at[1:].tolist(), strict=True)):
        if b - a >= k:
            s = np.sort(all_grams[a : b - k + 1])
            s = s[np.concatenate(([True], s[1:] != s[:-1]))]
        elif b > a:
            s = mix((w.hashes[a:b] * LANE[: b - a]).sum(dtype=np.uint64, keepdims=True) + _U(b - a))
        else:
            continue
        parts.append(s)
        sizes[r] = len(s)
    return (np.concatenate(parts) if parts else np.zeros(0, np.uint64)), np.concatenate(([0], np.cumsum(sizes)))
