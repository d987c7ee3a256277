"""Substring dedup by De Bruijn compaction.

Every window of ``span`` words is an edge of a De Bruijn graph over token k-mers. Windows that
follow one another and share their minimizer (the least hash of the k-mers inside, with
k = (span + 1) / 2) form one nonbranching path; a path stands for all its windows, about ten
times fewer rows. Equal passages give equal paths but at their ends, where contexts differ. So:

1. K-mers that are the minimizer of more than one path, or of a path that meets itself, are kept.
2. Their paths are compacted by content. A path seen twice repeats with all its windows.
3. A k-mer with several different paths branches: one representative of each path lists its single
   windows, joined by window hash and weighted by how often the path occurs.
4. Repeated windows go back, by source coordinates, to each distinct document as word spans. The words at
   these coordinates are compared by 128-bit digests: a path counts as repeated only if the same words stand at two
   of its places, a window likewise. Words that confirmed spans cover are removed.

Documents are known by a 128-bit digest of their text, so equal ones share all work. Bit sets of at most 4 MB
keep rows that cannot matter out of the shuffles until they are full (some millions of k-mers, paths or documents);
exact joins decide, and beyond that size all paths travel.

Null or blank text has no words and the digest of the empty string. Repeated rows are copies of
each other like any others. Null doc_id is kept; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.llm import bloom
from graphcc.llm import words as W
from graphcc.session import Kept

SPAN = 35
SCHEMA = "doc_id long, n_words long, n_removed long, kept_sha256 string"
_U = np.uint64


def _prefix(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    up, down = W._tables(len(h) + 1)
    c = np.zeros(len(h) + 1, np.uint64)
    np.cumsum(h * up[: len(h)], out=c[1:])
    return c, down


def row_keys(col: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """A 128-bit digest of each text, and its first half as a number, by which bit sets know it."""
    raw, at = W.text_buffer(col)
    data = memoryview(np.ascontiguousarray(raw))
    keys = [hashlib.md5(data[a:b], usedforsecurity=False).digest() for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
    return pa.array(keys, pa.binary()), np.frombuffer(b"".join(keys), "<i8")[::2].copy()


class Spaced:
    """The words of a slice with one space between any two, to be compared as they are."""

    def __init__(self, w: W.Words):
        size = w.ends - w.starts
        self.starts = np.concatenate(([0], np.cumsum(size + 1)))[:-1]
        self.ends = self.starts + size
        out = np.full(int(self.ends[-1]) + 1 if len(size) else 0, 32, np.uint8)
        out[self._inside(len(out), self.starts, self.ends)] = w.data[self._inside(len(w.data), w.starts, w.ends)]
        self.data = memoryview(out)

    @staticmethod
    def _inside(n: int, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        mark = np.zeros(n + 1, np.int8)
        mark[starts] += 1
        mark[ends] -= 1
        return np.cumsum(mark[:-1], dtype=np.int8) > 0

    def digests(self, first: np.ndarray, words: np.ndarray) -> pa.Array:
        """128 bits for each run of ``words`` words from ``first`` on."""
        a, b = self.starts[first].tolist(), self.ends[first + words - 1].tolist()
        return pa.array([hashlib.md5(self.data[x:y], usedforsecurity=False).digest() for x, y in zip(a, b, strict=True)], pa.binary())


class Paths:
    """The paths of a slice: row, first window (in words of the slice), windows, minimizer, content, meets itself."""

    def __init__(self, w: W.Words, span: int = SPAN):
        k = (span + 1) // 2
        wide, n = span - k + 1, len(w.hashes) - span + 1
        self.first = np.zeros(0, np.int64)
        self.row = self.size = self.first
        self.h = self.sw = np.zeros(0, np.uint64)
        self.multi = np.zeros(0, bool)
        self.c, self.down = _prefix(w.hashes)
        self.span = span
        if n <= 0:
            return
        m = W.rolling(w.hashes, k)
        low, have = m, 1
        while 2 * have <= wide:
            low = np.minimum(low[:-have], low[have:])
            have *= 2
        if have < wide:
            low = np.minimum(low[: len(low) - (wide - have)], low[wide - have :])
        rows = w.rows()
        s = np.flatnonzero(rows[:n] == rows[span - 1 :])
        if not len(s):
            return
        v, again = low[s], np.zeros(len(s), np.uint8)
        for j in range(wide):
            again += m[s + j] == v
        new = np.concatenate(([True], (np.diff(s) != 1) | (v[1:] != v[:-1])))
        at = np.flatnonzero(new)
        self.first, self.row, self.h = s[at], rows[s[at]], v[at]
        self.size = np.diff(np.append(at, len(s)))
        self.multi = (np.maximum.reduceat(again, at) > 1) | (self.size > wide)
        end = self.first + self.size - 1 + span
        self.sw = W.mix((self.c[end] - self.c[self.first]) * self.down[self.first] + self.size.astype(np.uint64) * W.LANE[7])

    def windows(self, i: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For the paths ``i``: index into ``i``, number of the window in its path, window hash."""
        size = self.size[i]
        of = np.repeat(np.arange(len(i)), size)
        j = np.arange(len(of)) - np.repeat(np.cumsum(size) - size, size)
        s = self.first[i][of] + j
        return of, j, W.mix((self.c[s + self.span] - self.c[s]) * self.down[s])


def _i64(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64) if x.dtype == np.uint64 else x.astype(np.int64))


def _where(key: np.ndarray, a: np.ndarray) -> np.ndarray:
    """One number for a place: document key and word position."""
    return W.mix(key.view(np.uint64) + a.astype(np.uint64) * W.LANE[9]).view(np.int64)


def _scan(what: str, span: int, shared=None):
    """Rows of every slice of texts: what a step of the method needs, kept rows chosen by a bit set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mask = shared.value if shared is not None else None
        for batch in batches:
            for part in W.slices(batch):
                w = W.words(part.column("text"))
                p = Paths(w, span)
                a = p.first - w.at[:-1][p.row]
                if what == "minimizers":
                    yield pa.RecordBatch.from_arrays([_i64(p.h), pa.array(p.multi.astype(np.int32))], ["h", "multi"])
                    continue
                doc, key = row_keys(part.column("text"))
                tested = {"paths": p.h.view(np.int64), "windows": _where(key[p.row], a), "places": p.sw.view(np.int64)}[what]
                i = np.flatnonzero(bloom.holds(tested, mask))
                if not len(i):
                    continue
                if what == "windows":
                    yield _window_rows(w, p, i)
                elif what == "paths":
                    cols = [_i64(p.h[i]), _i64(p.sw[i]), pa.array(p.multi[i].astype(np.int32)), _i64(key[p.row[i]]), _i64(a[i])]
                    yield pa.RecordBatch.from_arrays(cols, ["h", "sw", "multi", "key", "a"])
                else:
                    said = Spaced(w).digests(p.first[i], p.size[i] - 1 + span)
                    cols = [_i64(p.h[i]), _i64(p.sw[i]), pa.array(p.size[i].astype(np.int32)), doc.take(pa.array(p.row[i])), _i64(a[i]), said]
                    yield pa.RecordBatch.from_arrays(cols, ["h", "sw", "size", "doc", "a", "said"])

    return run


_PATHS = "h long, sw long, multi int, key long, a long"
_PLACES = "h long, sw long, size int, doc binary, a long, said binary"
_WINDOWS = "h long, sw long, j int, w long, said binary"


def _window_rows(w: W.Words, p: Paths, i: np.ndarray) -> pa.RecordBatch:
    """The single windows of the paths ``i``."""
    of, j, hashes = p.windows(i)
    said = Spaced(w).digests(p.first[i][of] + j, np.full(len(of), p.span))
    return pa.RecordBatch.from_arrays([_i64(p.h[i][of]), _i64(p.sw[i][of]), pa.array(j.astype(np.int32)), _i64(hashes), said], ["h", "sw", "j", "w", "said"])


def _windows(texts: DataFrame, branches: DataFrame, span: int, by_join: bool) -> DataFrame:
    """Single windows of the representatives: found by a bit set while one can hold them all, else by a join on documents."""
    if not by_join:
        ones = texts.sparkSession.sparkContext.broadcast(bloom.build(branches.mapInArrow(_place_of, "place long"), branches.count()))
        return texts.mapInArrow(_scan("windows", span, ones), _WINDOWS)
    at = Kept(branches.groupBy("key").agg(F.collect_set("a").alias("at")), "places").df
    keyed = texts.mapInArrow(_keyed, "text string, key long, doc binary").dropDuplicates(["key", "doc"])
    return keyed.join(at, "key").select("text", "at").mapInArrow(_windows_at(span), _WINDOWS)


def _keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part in W.slices(batch):
            doc, key = row_keys(part.column("text"))
            yield pa.RecordBatch.from_arrays([part.column("text"), pa.array(key), doc], ["text", "key", "doc"])


def _windows_at(span: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in W.slices(batch):
                w = W.words(part.column("text"))
                p = Paths(w, span)
                wanted = [np.array(x, np.int64) for x in part.column("at").to_pylist()]
                rows = np.repeat(np.arange(len(wanted)), [len(x) for x in wanted])
                at = w.at[:-1][rows] + np.concatenate(wanted)
                yield _window_rows(w, p, np.flatnonzero(np.isin(p.first, at)))

    return run


def repeated_spans(texts: DataFrame, span: int = SPAN, most_bits: int = 1 << bloom.MOST) -> DataFrame:
    """``(doc, spans array<struct<a, size, js>>)`` of each distinct text with a repeated window, ``doc`` its digest.

    ``js`` null: all ``size`` windows from word ``a`` on are repeated; else those at ``a + j``.
    """
    texts = texts.select("text")
    sc = texts.sparkSession.sparkContext
    minimizers = texts.mapInArrow(_scan("minimizers", span), "h long, multi int")
    kept = Kept(minimizers.groupBy("h").agg(F.count(F.lit(1)).alias("c"), F.max("multi").alias("m")).where("c > 1 OR m > 0").select("h"), "kmers")
    some = sc.broadcast(bloom.build(kept.df, kept.df.count()))
    paths = texts.mapInArrow(_scan("paths", span, some), _PATHS)
    compact = paths.groupBy("h", "sw").agg(F.count(F.lit(1)).alias("n"), F.max("multi").alias("multi"), F.min("key").alias("key"), F.min_by("a", "key").alias("a"))
    compact = Kept(compact, "paths")
    branching = compact.df.groupBy("h").agg(F.count(F.lit(1)).alias("k"), F.max("multi").alias("m")).where("k > 1 OR m > 0").select("h")
    branches = Kept(compact.df.join(branching, "h", "left_semi"), "branches")
    single = _windows(texts, branches.df, span, branches.df.count() * 16 > most_bits).dropDuplicates(["sw", "j", "h", "w", "said"])
    single = Kept(single.join(branches.df.select("h", "sw", "n"), ["h", "sw"]), "windows")
    twice = single.df.groupBy("h", "w", "said").agg(F.sum("n").alias("t")).where("t > 1").select("h", "w", "said")
    twice = Kept(twice, "repeated")
    partly = single.df.where("n = 1").join(twice.df, ["h", "w", "said"], "left_semi").groupBy("h", "sw").agg(F.collect_set("j").alias("js"))
    whole = compact.df.where("n > 1").select("h", "sw", F.lit(None).cast("array<int>").alias("js"))
    repeats = Kept(whole.unionByName(partly), "repeats")
    seen = sc.broadcast(bloom.build(repeats.df.select("sw"), repeats.df.count()))
    places = texts.mapInArrow(_scan("places", span, seen), _PLACES).groupBy("h", "sw", "size", "doc", "a", "said").agg(F.count(F.lit(1)).alias("n"))
    found = Kept(places.join(repeats.df, ["h", "sw"]), "places")
    same = found.df.where("js IS NULL").groupBy("h", "sw", "said").agg(F.sum("n").alias("t")).where("t > 1").select("h", "sw", "said")
    sure = found.df.where("js IS NULL").join(same, ["h", "sw", "said"], "left_semi").unionByName(found.df.where("js IS NOT NULL"))
    out = Kept(sure.groupBy("doc").agg(F.collect_list(F.struct("a", "size", "js")).alias("spans")), "spans")
    for t in (kept, compact, branches, single, twice, repeats, found):
        t.drop()
    return out.df


def _half(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(b"".join(b.column(0).to_pylist()), "<i8")[::2])], ["key"])


def _place_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield pa.RecordBatch.from_arrays([pa.array(_where(b.column("key").to_numpy(), b.column("a").to_numpy()))], ["place"])


def _kept(part: pa.RecordBatch, w: W.Words, removed: np.ndarray, texts: bool) -> pa.RecordBatch:
    """Words not ``removed``, joined by single spaces."""
    data, rows = w.data.copy(), w.rows()
    data[w.ends[:-1][rows[1:] == rows[:-1]]] = 32  # any spacing after a word, but not the next row's first byte
    keep = ~removed
    total = np.concatenate(([0], np.cumsum(keep)))
    left = total[w.at[1:]] - total[w.at[:-1]]
    kept = np.flatnonzero(keep)
    last = total[w.at[1:]][left > 0] - 1  # of each row, among the kept words
    tail = np.ones(len(kept), np.int64)
    tail[last] = 0
    length = w.ends[kept] - w.starts[kept] + tail
    mark = np.zeros(len(data) + 1, np.int8)  # bytes that stay: words with one byte of spacing
    mark[w.starts[kept]] += 1
    mark[w.starts[kept] + length] -= 1
    out = data[np.cumsum(mark[:-1], dtype=np.int8) > 0].tobytes()
    ends = np.concatenate(([0], np.cumsum(length)))[total[w.at]]
    pieces = [out[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
    cols = [part.column("doc_id"), pa.array(w.counts), pa.array(w.counts - left), pa.array([hashlib.sha256(x).hexdigest() for x in pieces])]
    names = ["doc_id", "n_words", "n_removed", "kept_sha256"]
    if texts:
        cols.append(pa.array([x.decode() for x in pieces]))
        names.append("kept_text")
    return pa.RecordBatch.from_arrays(cols, names)


def _untouched(shared, inverse: bool, texts: bool):
    """Rows surely without spans, finished at once; with ``inverse`` the others, with their keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in W.slices(batch):
                w = W.words(part.column("text"))
                doc, key = row_keys(part.column("text"))
                may = bloom.holds(key, shared.value)
                if inverse:
                    yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text"), doc], ["doc_id", "text", "doc"]).filter(pa.array(may))
                else:
                    yield _kept(part, w, np.zeros(len(w.starts), bool), texts).filter(pa.array(~may))

    return run


def _cut(span: int, texts: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in W.slices(batch):
                w = W.words(part.column("text"), hashed=False)
                step = np.zeros(len(w.starts) + 1, np.int64)
                for first, spans in zip(w.at[:-1].tolist(), part.column("spans").to_pylist(), strict=True):
                    for s in spans or ():
                        for a, n in [(s["a"], s["size"])] if s["js"] is None else [(s["a"] + j, 1) for j in s["js"]]:
                            step[first + a] += 1
                            step[first + a + n - 1 + span] -= 1
                yield _kept(part, w, np.cumsum(step[:-1]) > 0, texts)

    return run


def dedup_substrings(docs: DataFrame, span: int = SPAN, texts: bool = False, most_bits: int = 1 << bloom.MOST) -> DataFrame:
    """``(doc_id, n_words, n_removed, kept_sha256)`` of every row, with ``kept_text`` on request."""
    docs = docs.select("doc_id", "text")
    spans = repeated_spans(docs, span, most_bits)
    may = docs.sparkSession.sparkContext.broadcast(bloom.build(spans.select("doc").mapInArrow(_half, "key long"), spans.count()))
    schema = SCHEMA + ", kept_text string" * texts
    clean = docs.mapInArrow(_untouched(may, False, texts), schema)
    rest = docs.mapInArrow(_untouched(may, True, texts), "doc_id long, text string, doc binary").join(spans, "doc", "left")
    return clean.unionByName(rest.select("doc_id", "text", "spans").mapInArrow(_cut(span, texts), schema))
