"""Quality classifier: logistic regression on hashed word n-grams, trained with FTRL.

Words are cut at spaces and between letters and other signs, so that decoration and
shouting become words of their own; single words and pairs are hashed into a fixed
table. A text's vector is binary with unit length. Weights come from
follow-the-regularised-leader updates over a bounded sample of labelled documents
(``sample_rows``, chosen by hash; the scan stays distributed and the updates run in one
task whose rows that bound limits). Scores are sparse dot products over the whole texts.

Empty or null text: no words, so the score is the bias alone. Labels that are null are
not learnt from; a document labelled twice counts with its larger label. Without usable
labels every score is 0.5. Repeated documents are scored each; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.llm import words as W

BITS = 18
SCHEMA = "doc_id long, held_out boolean, score double, predicted int"


def features(col: pa.Array, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed single words and pairs of each row: all indices, and row offsets."""
    w = W.words(col, by_kind=True)
    rows, drop = w.rows(), np.uint64(64 - bits)
    one = W.mix(w.hashes + np.uint64(1)) >> drop
    two = W.grams(w.hashes, 2)[rows[1:] == rows[:-1]] >> drop if len(rows) > 1 else np.zeros(0, np.uint64)
    key = np.concatenate([rows, rows[1:][rows[1:] == rows[:-1]]]).astype(np.int64) << bits | np.concatenate([one, two]).astype(np.int64)
    key.sort()
    key = key[np.concatenate(([True], key[1:] != key[:-1]))] if len(key) else key
    return key & ((1 << bits) - 1), np.searchsorted(key >> bits, np.arange(len(w.at)))


class Ftrl:
    """Per-coordinate FTRL-proximal with L1 and L2 regularisation; the last coordinate is the bias."""

    def __init__(self, dims: int, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.02, l2: float = 0.1):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros(dims), np.zeros(dims)

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) <= self.l1, 0.0, (np.sign(z) * self.l1 - z) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, x: float, label: int, bias: int) -> None:
        at = np.append(at, bias)
        value = np.full(len(at), x)
        value[-1] = 1.0
        w = self.weights(at)
        g = (1 / (1 + np.exp(-float(w @ value))) - label) * value
        self.z[at] += g - (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.alpha * w
        self.n[at] += g * g


def _extract(bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in W.slices(batch):
                idx, at = features(part.column("text"), bits)
                lists = pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(idx, pa.int32()))
                yield pa.RecordBatch.from_arrays([part.column("rank"), part.column("quality"), lists], ["rank", "quality", "features"])

    return run


def _train(bits: int, epochs: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [(y, f.values.to_numpy()) for b in batches for y, f in zip(b.column("quality").to_pylist(), b.column("features"), strict=True)]
        model = Ftrl((1 << bits) + 1)
        for _ in range(max(epochs, min(20, 12_000 // max(1, len(rows))))):  # more passes over few rows
            for y, at in rows:
                model.learn(at, 1 / np.sqrt(max(1, len(at))), y, 1 << bits)
        yield pa.RecordBatch.from_arrays([pa.array([model.weights().astype("<f4").tobytes()], pa.binary())], ["weights"])

    return run


def bucket(doc_id="doc_id"):
    """The fold of a document: crc32 of its id as text, modulo 4."""
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(4))


def train(docs: DataFrame, labels: DataFrame, bits: int = BITS, sample_rows: int = 8000, epochs: int = 3, hold_out: int | None = 2) -> np.ndarray:
    """Weights (2**bits and a bias) learnt from labelled documents outside the held-out fold."""
    known = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull())
    if hold_out is not None:
        known = known.where(bucket() != hold_out)
    known = known.groupBy("doc_id").agg(F.max("quality").alias("quality")).withColumn("rank", F.xxhash64("doc_id"))
    share = min(1.0, sample_rows / max(1, known.count()))
    top = min(2**63 - 1, int((2 * share - 1) * 2**63))
    chosen = known.where(F.col("rank") <= top)  # about sample_rows of them, so small enough to broadcast
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("rank", "quality", "text")
    feats = sample.mapInArrow(_extract(bits), "rank long, quality int, features array<int>")
    got = feats.repartition(1).sortWithinPartitions("rank", F.hash("features")).mapInArrow(_train(bits, epochs), "weights binary").collect()
    return np.frombuffer(bytes(got[0].weights), "<f4") if got else np.zeros((1 << bits) + 1, "<f4")


def _scorer(weights, bits: int, passed: int, into: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = weights.value
        for batch in batches:
            for part in W.slices(batch):
                idx, at = features(part.column("text"), bits)
                sums = np.concatenate(([0.0], np.cumsum(w[idx], dtype=np.float64)))
                size = np.diff(at)
                dot = (sums[at[1:]] - sums[at[:-1]]) / np.sqrt(np.maximum(1, size)) + float(w[-1])
                score = np.round(1 / (1 + np.exp(-np.clip(dot, -500, 500))), 9)
                yield pa.RecordBatch.from_arrays([*part.columns[:passed], pa.array(score)], [*part.schema.names[:passed], into])

    return run


def score(docs: DataFrame, weights: np.ndarray, bits: int = BITS, into: str = "score") -> DataFrame:
    """All columns of ``docs``, and ``into`` (in place of one of that name): the probability that the text is labelled 1."""
    docs = docs.drop(into)
    shared = docs.sparkSession.sparkContext.broadcast(weights)  # 2**bits floats, whatever the corpus
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema) + f", `{into}` double"
    return docs.mapInArrow(_scorer(shared, bits, len(docs.columns), into), schema)
