"""Brute-force twins and the awkward rows every operator must take."""

import collections
import re

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def documents(spark, texts, first=0, sources=None, extra=False):
    rows = [(first + i, t, "en", (sources[i] if sources else "s"), len(t or "")) for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, SCHEMA)
    if extra:  # names that the operators use inside
        from pyspark.sql import functions as F

        for name in ("token", "score", "size", "hub", "key", "line", "n", "position", "keys", "spans"):
            df = df.withColumn(name, F.lit("clash"))
    return df


def words(text):
    return WORD.findall(text or "")


def shingles(text, k):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (text or ""))
    w = words(low)
    if not w:
        return frozenset()
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)])


def jaccard_components(rows, k, percent):
    sets = {}
    for d, t in rows:
        sets.setdefault(d, set()).add(shingles(t, k))
    items = [(d, s) for d, ss in sets.items() for s in ss if s]
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, (a, x) in enumerate(items):
        for b, y in items[:i]:
            m = len(x & y)
            if 100 * m >= percent * (len(x) + len(y) - m):
                ra, rb = find(a), find(b)
                parent[max(ra, rb)] = min(ra, rb)
    return {d: find(d) for d in sets}


def removed_words(rows, span):
    ws = [(d, words(t)) for d, t in rows]
    seen = collections.Counter(tuple(w[i : i + span]) for _, w in ws for i in range(len(w) - span + 1))
    out = []
    for d, w in ws:
        gone = [False] * len(w)
        for i in range(len(w) - span + 1):
            if seen[tuple(w[i : i + span])] > 1:
                gone[i : i + span] = [True] * span
        out.append((d, len(w), sum(gone), " ".join(x for x, g in zip(w, gone, strict=True) if not g)))
    return sorted(out)


def edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]
