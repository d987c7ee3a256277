"""URL filters over a sorted digest array.

The rule file holds the sorted 64-bit xxhash keys of all rules, memory-mapped by
every Python worker, beside the rules' full strings and their verdicts. A url is
probed with those parent domains of its host, and those prefixes of its path, that have the lengths of a
rule's host and path, so a url of any length has as many probes as rules have kinds of lengths; probes are
answered by one vectorised binary search, and a hit counts only if the stored string is equal. The longest rule wins.

Null url, or none with ``://``: host and path empty, no rule. Repeated rows and
null page_id are kept; extra columns are ignored; an empty table gives no rows. Very long
urls are judged like others. A rule is (host, path, verdict) and fits its host and all subdomains.
"""

from __future__ import annotations

import hashlib
import os
import tempfile
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession

#: The rules of the contract.
RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]
SCHEMA = "page_id long, host string, path string, rule string, verdict string"
_HEAD = np.dtype([("rules", "<i8"), ("pairs", "<i8")])
_UPPER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def write_rules(rules: Iterable[tuple[str, str, str]], path: str) -> None:
    """The file: header, pairs of lengths that rules' hosts and paths have, sorted keys, string offsets, block flags, strings."""
    rules = list(rules)
    best = {h + p: v for h, p, v in rules}
    pairs = np.array(sorted({(len(h.encode()), len(p.encode())) for h, p, _ in rules}), "<i8").reshape(-1, 2)
    order = sorted((xxhash.xxh64_intdigest(s), s) for s in best)
    strings = [s.encode() for _, s in order]
    with open(path, "wb") as f:
        f.write(np.array([(len(order), len(pairs))], _HEAD).tobytes() + pairs.tobytes())
        f.write(np.array([k for k, _ in order], "<u8").tobytes())
        f.write(np.cumsum([0, *map(len, strings)]).astype("<i8").tobytes())
        f.write(bytes(best[s] == "block" for _, s in order) + b"".join(strings))


class DigestArray:
    """A rule file, mapped into memory; several workers of a machine share its pages."""

    _open: dict[str, DigestArray] = {}

    def __init__(self, path: str):
        raw = np.memmap(path, np.uint8, "r")
        n, m = (int(x) for x in raw[:16].view("<i8"))
        at = 16
        self.sizes = [tuple(x) for x in raw[at : at + 16 * m].view("<i8").reshape(-1, 2).tolist()]
        at += 16 * m
        self.keys = raw[at : at + 8 * n].view("<u8")
        at += 8 * n
        self.offsets = raw[at : at + 8 * (n + 1)].view("<i8")
        at += 8 * (n + 1)
        self.block, self.strings = raw[at : at + n], raw[at + n :]

    @classmethod
    def load(cls, path: str) -> DigestArray:
        if path not in cls._open:
            cls._open[path] = cls(path)
        return cls._open[path]

    def string(self, i: int) -> bytes:
        return self.strings[self.offsets[i] : self.offsets[i + 1]].tobytes()

    def find(self, probes: list[bytes]) -> np.ndarray:
        """Index of each probe's rule, -1 without one; equal keys are told apart by their strings."""
        out = np.full(len(probes), -1, np.int64)
        if not probes or not len(self.keys):
            return out
        keys = np.fromiter(map(xxhash.xxh64_intdigest, probes), np.uint64, len(probes))
        at = np.searchsorted(self.keys, keys)
        hit = np.flatnonzero(self.keys[np.minimum(at, len(self.keys) - 1)] == keys)
        for i in hit.tolist():
            j = int(at[i])
            while j < len(self.keys) and self.keys[j] == keys[i]:
                if self.string(j) == probes[i]:
                    out[i] = j
                    break
                j += 1
        return out


def split_url(url: str | None) -> tuple[str, str]:
    """Host (A-Z lower-cased) and path, both empty without ``://``."""
    if url is None or (at := url.find("://")) < 0:
        return "", ""
    rest = url[at + 3 :]
    end = min((i for i in map(rest.find, "?#") if i >= 0), default=len(rest))
    rest = rest[:end]
    slash = rest.find("/")
    host, path = (rest, "") if slash < 0 else (rest[:slash], rest[slash:])
    return host.translate(_UPPER), path


def _probes(host: str, path: str, sizes: list[tuple[int, int]]) -> list[bytes]:
    """Longest first; the parent domains of the host and prefixes of the path that are as long as a rule's."""
    if not host:
        return []
    name, raw, out = host.encode(), path.encode(), []
    for h, p in sizes:
        if p <= len(raw) and (h == len(name) or 0 < h < len(name) and name[-h - 1] == 46):  # a dot before it
            out.append(name[len(name) - h :] + raw[:p])
    return sorted(out, key=len, reverse=True)


def _judge(name: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rules = DigestArray.load(SparkFiles.get(name))
        for batch in batches:
            split = [split_url(u) for u in batch.column(1).to_pylist()]
            each = [_probes(h, p, rules.sizes) for h, p in split]
            found = rules.find([p for ps in each for p in ps])
            rule, verdict, at = [], [], 0
            for ps in each:
                hit = next((int(j) for j in found[at : at + len(ps)] if j >= 0), -1)
                at += len(ps)
                rule.append(rules.string(hit).decode() if hit >= 0 else None)
                verdict.append("block" if hit >= 0 and rules.block[hit] else "allow")
            host, path = zip(*split, strict=True) if split else ((), ())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), pa.array(host, pa.string()), pa.array(path, pa.string()), pa.array(rule, pa.string()), pa.array(verdict, pa.string())],
                ["page_id", "host", "path", "rule", "verdict"],
            )

    return run


def judge_urls(spark: SparkSession, pages: DataFrame, rules: Iterable[tuple[str, str, str]] = RULES) -> DataFrame:
    """``(page_id, host, path, rule, verdict)``; a url that no rule fits is not in the array and so allowed."""
    rules = list(rules)
    name = f"url-rules-{hashlib.sha256(repr(rules).encode()).hexdigest()[:16]}.bin"
    folder = os.path.join(tempfile.gettempdir(), f"graphcc-rules-{os.getpid()}")
    os.makedirs(folder, exist_ok=True)
    path = os.path.join(folder, name)
    if not os.path.exists(path):
        part = f"{path}.{uuid.uuid4().hex[:8]}"
        write_rules(rules, part)
        os.replace(part, path)  # whole or not at all
    spark.sparkContext.addFile(path)  # Spark's file server takes it to each executor once
    return pages.select("page_id", "url").mapInArrow(_judge(name), SCHEMA)
