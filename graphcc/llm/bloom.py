"""Bit sets of bounded size that keep surely useless rows out of a later scan.

They never lose a row: what passes by chance is removed by the exact join that follows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.llm.words import mix

#: 2**LEAST to 2**MOST bits (4 MB at most), so that a broadcast is always small.
LEAST, MOST = 18, 25
_SEED = np.uint64(0x8CB92BA72F3D8DD7)


def _at(keys: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    h = mix(keys.astype(np.int64).view(np.uint64) + _SEED)
    return (h >> np.uint64(64 - bits)).astype(np.int64), ((h << np.uint64(30)) >> np.uint64(64 - bits)).astype(np.int64)


def holds(keys: np.ndarray, mask: np.ndarray) -> np.ndarray:
    """Which int64 keys may be in the set; False is certain."""
    bit = lambda x: mask[x >> 3] >> (x & 7).astype(np.uint8) & 1
    a, b = _at(keys, (len(mask) * 8).bit_length() - 1)
    return (bit(a) & bit(b)).astype(bool)


def _part(bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mask = np.zeros(1 << (bits - 3), np.uint8)
        for batch in batches:
            for x in _at(batch.column(0).to_numpy(), bits):
                np.bitwise_or.at(mask, x >> 3, np.uint8(1) << (x & 7).astype(np.uint8))
        words = mask.view(np.int64)
        w = np.flatnonzero(words)
        yield pa.RecordBatch.from_arrays([pa.array(w.astype(np.int32)), pa.array(words[w])], ["w", "bits"])

    return run


def build(keys: DataFrame, rows: int | None = None, most: int = MOST) -> np.ndarray:
    """The set of a one-column DataFrame of LONG, 16 bits a row up to 2**most in all."""
    bits = min(most, max(LEAST, (16 * rows).bit_length())) if rows is not None else most
    per = keys.mapInArrow(_part(bits), "w int, bits long").groupBy("w").agg(F.bit_or("bits").alias("bits")).toPandas()
    out = np.zeros(1 << (bits - 6), np.int64)
    out[per["w"].to_numpy(np.int64)] = per["bits"].to_numpy(np.int64)
    return out.view(np.uint8)
