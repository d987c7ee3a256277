"""Packing documents into fixed windows by best-fit decreasing.

Every document becomes its token ids followed by one end id. Overlong documents are
first cut into full windows; what is left is placed, longest piece first, into the
tightest open window, found by a segment tree over remaining capacities. Each task
packs the documents it reads, so nothing is shuffled and a retried task gives the
same rows; a task leaves a few unfilled windows, whatever the size of the corpus.

Null or empty text: the end id alone. Repeated rows are packed as often as they occur;
null doc_id is kept. Extra columns are ignored. An empty table gives no rows.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

WINDOW, END_ID = 2048, 1
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
#: Fixed value: the split pattern of the public byte-level BPE.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Characters on whose class all Unicode versions agree; other texts take the slower library.
_OTHER = re.compile("[^\x00-ɏΑ-ΡΣ-ώЀ-џ‐-‧€]|<\\|endoftext\\|>")
_CUT = re.compile(r"(?<=[a-z]) (?=[A-Za-z])")
_LONG = 1 << 20


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Tokenizer:
    """Ids as ``tokenizers`` gives them; most texts go through a faster encoder of the same vocabulary."""

    _loaded: dict[str, Tokenizer] = {}

    def __init__(self, path: str):
        import tiktoken

        self.path = path
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        byte = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in shown)}
        extra = {t["content"] for t in spec.get("added_tokens", [])}
        ranks = {bytes(byte[c] for c in t): i for t, i in spec["model"]["vocab"].items() if t not in extra}
        self.fast = tiktoken.Encoding("from_file", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})

    @cached_property
    def exact(self):
        """The reference library, loaded when a text first needs it."""
        import tokenizers

        return tokenizers.Tokenizer.from_file(self.path)

    @classmethod
    def load(cls, path: str) -> Tokenizer:
        if path not in cls._loaded:
            cls._loaded[path] = cls(path)
        return cls._loaded[path]

    def _parts(self, text: str) -> Iterator[str]:
        """A long text in parts between which no token can lie."""
        a = 0
        while len(text) - a > _LONG:
            m = _CUT.search(text, a + _LONG)
            if not m:
                break
            yield text[a : m.start()]
            a = m.start()
        yield text[a:] if a else text

    def ids(self, text: str) -> np.ndarray:
        if _OTHER.search(text):
            return np.array(self.exact.encode(text, add_special_tokens=False).ids, "<u4")
        return np.concatenate([np.array(self.fast.encode_ordinary(x), "<u4") for x in self._parts(text)])


class BestFit:
    """Open windows by remaining capacity; a segment tree finds the least capacity that suffices."""

    def __init__(self, window: int = WINDOW):
        self.window, self.leaves = window, 1 << window.bit_length()
        self.tree = bytearray(2 * self.leaves)  # node: any open window below it
        self.open: list[list[int]] = [[] for _ in range(window + 1)]
        self.made = 0

    def _mark(self, capacity: int) -> None:
        i, filled = self.leaves + capacity, bool(self.open[capacity])
        self.tree[i] = filled
        while i > 1:
            i >>= 1
            any_below = self.tree[2 * i] or self.tree[2 * i + 1]
            if self.tree[i] == any_below:
                break
            self.tree[i] = any_below

    def tightest(self, need: int) -> int:
        """The least capacity of an open window that is at least ``need``, or 0."""
        i = self.leaves + need
        if self.tree[i]:
            return need
        while i > 1:
            if not i & 1 and self.tree[i + 1]:
                i += 1
                while i < self.leaves:
                    i = 2 * i + (not self.tree[2 * i])
                return i - self.leaves
            i >>= 1
        return 0

    def place(self, need: int) -> tuple[int, int]:
        """Window and offset of a piece."""
        if capacity := self.tightest(need):
            w = self.open[capacity].pop()
            if not self.open[capacity]:
                self._mark(capacity)
        else:
            w, capacity = self.made, self.window
            self.made += 1
        if left := capacity - need:
            self.open[left].append(w)
            if len(self.open[left]) == 1:
                self._mark(left)
        return w, self.window - capacity


def pack_lengths(lengths: np.ndarray, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray, int]:
    """Window and offset of each length (all at most ``window``), and the number of windows."""
    fit, seq, off = BestFit(window), np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    for i in np.argsort(-np.asarray(lengths), kind="stable").tolist():
        seq[i], off[i] = fit.place(int(lengths[i]))
    return seq, off, fit.made


def _packer(path: str, window: int, end_id: int, most: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, first = Tokenizer.load(path), TaskContext.get().partitionId() << 36
        rows: list[tuple] = []

        def flush() -> pa.RecordBatch:
            nonlocal first
            doc, start, length, crc, total = zip(*rows, strict=True)
            seq, off, made = pack_lengths(np.array(length), window)
            out = pa.RecordBatch.from_arrays(
                [pa.array(x, pa.int64()) for x in (doc, start, length, crc, total, seq + first, off)],
                ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"],
            )
            first += made
            rows.clear()
            return out

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.append(tok.ids(text.as_py() or ""), np.uint32(end_id)).astype("<u4")
                for a in range(0, len(ids), window):
                    piece = ids[a : a + window]
                    rows.append((doc, a, len(piece), zlib.crc32(piece.tobytes()), len(ids)))
            if len(rows) >= most:
                yield flush()
        if rows:
            yield flush()

    return run


def pack(docs: DataFrame, path: str | None = None, window: int = WINDOW, end_id: int = END_ID, pieces_at_once: int = 1 << 18) -> DataFrame:
    """Pieces of ``docs(doc_id, text)`` with the window (``sequence_id``) and offset each one lies at."""
    return docs.select("doc_id", "text").mapInArrow(_packer(path or tokenizer_path(), window, end_id, pieces_at_once), SCHEMA)
