import hashlib
import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from graphcc.llm import bloom, jaccard, lines, substrings
from graphcc.llm import words as W
from tests.llm import util

R = random.Random(11)
VOCAB = ["".join(R.choice("abcdehinorst") for _ in range(R.randint(1, 7))) for _ in range(400)]


def prose(n, rng=R):
    return " ".join(rng.choice(VOCAB) for _ in range(n))


def test_words_match_a_regular_expression():
    texts = ["a bb  c\n", "", None, " x", "é ñ\tz\x0bq", "\x1cA\x85b", "w" * 3_000_000 + " tail"]
    w = W.words(pa.array(texts))
    for r, t in enumerate(texts):
        got = [bytes(w.data[s:e]).decode() for s, e in zip(w.starts[w.at[r] : w.at[r + 1]], w.ends[w.at[r] : w.at[r + 1]], strict=True)]
        assert got == util.words(t)
    again = W.words(pa.array(["q a", "a q"]))
    assert again.hashes[0] == again.hashes[3] and again.hashes[1] == again.hashes[2]


def test_lower_folds_only_ascii():
    a, b = (W.words(pa.array([t]), lower=True).hashes for t in ("ABZ É", "abz É"))
    assert (a == b).all()
    assert (W.words(pa.array(["É"]), lower=True).hashes != W.words(pa.array(["é"]), lower=True).hashes).all()


def test_bloom_loses_nothing(spark):
    keys = spark.range(1000).select((F.col("id") * 977).alias("k"))
    mask = bloom.build(keys, 1000)
    assert bloom.holds(np.arange(1000) * 977, mask).all()
    assert bloom.holds(np.arange(1_000_000, 1_010_000), mask).mean() < 0.1


@pytest.mark.parametrize(("k", "percent"), [(4, 85), (5, 80)])
def test_jaccard_components(spark, k, percent):
    rng = random.Random(5)
    texts = [None, "", "  \n", "one", "one two", "ONE two", "one two"]
    for _ in range(12):
        base = prose(rng.randint(3, 150), rng).split()
        texts += [" ".join(base)] * 2
        for _ in range(rng.randint(0, 6)):
            copy = list(base)
            for _ in range(rng.randint(1, 4)):
                copy[rng.randrange(len(copy))] = rng.choice(VOCAB)
            texts.append(" ".join(copy))
    shared = prose(12, rng)
    texts += [f"{shared} {prose(rng.randint(1, 12), rng)}" for _ in range(20)]
    docs = util.documents(spark, texts, first=3, extra=True)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.near_duplicates(docs, k, percent).collect()}
    want = util.jaccard_components([(3 + i, t) for i, t in enumerate(texts)], k, percent)
    assert {d: c for d, (_, c) in got.items()} == want
    assert all(got[3 + i][0] == len(util.shingles(t, k)) for i, t in enumerate(texts))


def test_jaccard_odd_rows(spark):
    rows = [(None, "a b c d e f", "x"), (7, "a b c d e f", "x"), (7, "a b c d e f", "x"), (None, None, "x"), (9, "q r s t u v w", "x")]
    got = sorted(((r.doc_id, r.n_shingles, r.component_id) for r in jaccard.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string, hub string"), 4, 85).collect()), key=str)
    assert got == sorted([(None, 3, 7), (7, 3, 7), (7, 3, 7), (None, 0, None), (9, 4, 9)], key=str)
    assert jaccard.near_duplicates(spark.createDataFrame([], util.SCHEMA)).count() == 0


def test_choose_l_lengthens_only_costly_prefixes():
    assert jaccard.choose_l(np.zeros(40), 100, 85) == 1
    assert jaccard.choose_l(np.full(40, 500.0), 100, 85) == jaccard.MOST_L
    assert jaccard.need(100, 85) == 85 and jaccard.need(7, 85) == 6


@pytest.mark.parametrize("most_bits", [1 << 25, 1])
def test_substrings(spark, most_bits):
    rng = random.Random(8)
    passage, other = prose(60, rng), prose(36, rng)
    texts = [None, "", " ", "la " * 90, "la " * 34, f"{prose(20, rng)} {passage} {prose(9, rng)}", f"{passage}", f"x {passage} y {other}\n{other}", prose(200, rng)]
    texts += [texts[-1], " ".join(texts[-1].split()[:100]), f"{other} {prose(34, rng)}", ("ab cd " * 40).strip(), passage.replace(" ", "\t ")]
    for _ in range(6):
        copy = passage.split()
        copy[rng.randrange(60)] = "edited"
        texts.append(" ".join(copy))
    docs = util.documents(spark, texts, extra=True)
    got = sorted((r.doc_id, r.n_words, r.n_removed, r.kept_text) for r in substrings.dedup_substrings(docs, texts=True, most_bits=most_bits).collect())
    assert got == util.removed_words(list(enumerate(texts)), 35)
    plain = {r.doc_id: r.kept_sha256 for r in substrings.dedup_substrings(docs, most_bits=most_bits).collect()}
    assert plain == {d: hashlib.sha256(t.encode()).hexdigest() for d, _, _, t in got}


def test_substrings_odd_rows(spark):
    text = prose(50)
    rows = [(None, text), (4, text), (4, text), (5, "short")]
    got = sorted(((r.doc_id, r.n_removed) for r in substrings.dedup_substrings(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    assert got == sorted([(None, 50), (4, 50), (4, 50), (5, 0)], key=str)
    assert substrings.dedup_substrings(spark.createDataFrame([], util.SCHEMA)).count() == 0


def test_banded_distance(spark):
    rng, rows = random.Random(3), []
    for _ in range(600):
        s = [rng.choice("abé") for _ in range(rng.randint(1, 30))]
        t = list(s)
        for _ in range(rng.randint(0, 4)):
            i = rng.randint(0, len(t))
            kind = rng.random()
            if kind < 0.4:
                t.insert(i, rng.choice("abé"))
            elif t:
                t[i : i + 1] = [] if kind < 0.7 else [rng.choice("abé")]
        a, b = "".join(s), "".join(t)
        rows.append((a, b) if len(a) >= len(b) else (b, a))
    df = spark.createDataFrame(rows, "a string, b string")
    for tau in (1, 2, 3):
        for r in df.select("a", "b", lines.banded_distance(F.col("a"), F.col("b"), tau).alias("d")).collect():
            true = util.edits(r.a, r.b)
            assert r.d == true if min(r.d, true) <= tau else r.d > tau


def test_line_dedup(spark):
    rng = random.Random(21)
    base = [prose(rng.randint(8, 20), rng) for _ in range(12)]

    def edited(s):
        s = list(s)
        for _ in range(rng.randint(1, 3)):
            i = rng.randrange(len(s))
            s[i : i + 1] = rng.choice(["", "zz", "q"])
        return "".join(s)

    texts = [None, "", "\n\n", "tiny\ntiny\ntiny"]
    texts += ["\n".join(rng.choice([x, edited(x), prose(9, rng), "same short line"]) for x in rng.sample(base, 5)) for _ in range(30)]
    first, judged = {}, {}
    seen = [(d, i, x) for d, t in enumerate(texts) for i, x in enumerate((t or "").split("\n")) if len(x) >= lines.EXACT_CHARS and x.strip()]
    for d, i, x in seen:
        first.setdefault(x, (d, i))
    for x in first:
        judged[x] = any(len(y) >= 32 and y != x and first[y] < first[x] and abs(len(y) - len(x)) <= 2 and util.edits(x, y) <= 2 for y in first) if len(x) >= 32 else False
    gone = {(d, i) for d, i, x in seen if judged[x] or first[x] != (d, i)}
    want = {}
    for d, t in enumerate(texts):
        kept = [x for i, x in enumerate((t or "").split("\n")) if (d, i) not in gone]
        dropped = any(g[0] == d for g in gone)
        if not dropped or "\n".join(kept).strip():
            want[d] = t if not dropped else "\n".join(kept)
    docs = util.documents(spark, texts, extra=True)
    out = lines.dedup_lines(docs)
    assert out.columns == docs.columns
    assert {r.doc_id: r.text for r in out.collect()} == want
    report = {r.doc_id: r for r in lines.line_report(docs).collect()}
    assert sum(r.exact_repeats + r.near_repeats for r in report.values()) == len(gone)
    assert lines.dedup_lines(spark.createDataFrame([], util.SCHEMA)).count() == 0


@pytest.mark.parametrize("doc_id", [7, None])
def test_line_dedup_keeps_rows_of_one_id_apart(spark, doc_id):
    texts = ["COMMON LINE\nunique b", "unique a\nCOMMON LINE", "COMMON LINE\nunique c"]
    docs = spark.createDataFrame([(doc_id, t) for t in texts] + [(-(2**63), "lowest id\nunique d")], "doc_id long, text string").coalesce(1)
    got = sorted(r.text for r in lines.dedup_lines(docs).collect())
    assert got == sorted(["COMMON LINE\nunique b", "unique a", "unique c", "lowest id\nunique d"])
    report = sorted((r.exact_repeats, r.near_repeats, r.kept_chars) for r in lines.line_report(docs).collect())
    assert report == [(0, 0, 17), (0, 0, 19), (1, 0, 8), (1, 0, 8)]
    same = spark.createDataFrame([(doc_id, "one text\nof two lines")] * 3, "doc_id long, text string")
    assert [r.text for r in lines.dedup_lines(same).collect()] == ["one text\nof two lines"]
    assert sorted(r.kept_chars for r in lines.line_report(same).collect()) == [0, 0, 20]


def test_line_dedup_of_short_lines(spark):
    long = "abcdefgh ijklmnop qrstuvwx yz01"  # 31 characters
    texts = ["Home\n\nContact us today\nabcdef", "Home\n\nContact us toda\nabcdXX\nab", "ab\nContact us tdoay\nabcdeg\nabcdegh\nHomes", long, long + "2\nown line", "q" + long + "2\nlast one"]
    seen = [(d, i, x) for d, t in enumerate(texts) for i, x in enumerate(t.split("\n")) if x.strip()]
    first = {}
    for d, i, x in seen:
        first.setdefault(x, (d, i))
    most = lambda x, y: 2 if min(len(x), len(y)) >= 32 else 1 if min(len(x), len(y)) >= 6 else 0
    near = {x for x in first if any(first[y] < first[x] and util.edits(x, y) <= most(x, y) for y in first)}
    gone = {(d, i) for d, i, x in seen if x in near or first[x] != (d, i)}
    want = {d: "\n".join(x for i, x in enumerate(t.split("\n")) if (d, i) not in gone) for d, t in enumerate(texts)}
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.text for r in lines.dedup_lines(docs, short=True).collect()}
    assert got == {d: t for d, t in want.items() if t.strip()} and len(gone) == 7


def test_line_dedup_is_native(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for df in (lines.dedup_lines(docs), lines.line_report(docs)):
        plan = df._jdf.queryExecution().toString()
        assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


def test_jaccard_links_through_rows_of_one_id(spark):
    one, two = "a b c d e f g h i j k l m n o p", "q r s t u v w x y z aa bb cc dd ee"
    rows = [(5, one), (5, two), (8, one + " z9"), (9, two + " z8"), (8, ""), (9, None), (11, None), (None, None)]
    rows += [(30, "m1 m2 m3 m4 m5 m6 m7 m8 m9"), (None, "m1 m2 m3 m4 m5 m6 m7 m8 m9 n1 n2"), (20, "m1 m2 m3 m4 m5 m6 m7 m8 m9 n1 n2 n3 n4")]
    got = sorted(((r.doc_id, r.component_id) for r in jaccard.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 4, 75).collect()), key=str)
    want = [(5, 5), (5, 5), (8, 5), (8, 5), (9, 5), (9, 5), (11, 11), (None, None), (30, 20), (None, 20), (20, 20)]
    assert got == sorted(want, key=str)


def test_sketch_grows_with_the_corpus_up_to_a_bound():
    assert [jaccard.sketch_bits_for(n) for n in (0, 1 << 20, 1 << 28, 1 << 40)] == [18, 18, 20, 20]


def test_spaced_words_are_compared_as_they_are():
    a, b = (W.words(pa.array([t])) for t in ("x  one\ttwo  three", "one two three four"))
    count = np.array([3])
    assert substrings.Spaced(a).digests(np.array([1]), count) == substrings.Spaced(b).digests(np.array([0]), count)
    assert substrings.Spaced(a).digests(np.array([0]), count) != substrings.Spaced(b).digests(np.array([0]), count)


def test_line_dedup_of_very_long_lines(spark):
    rng = random.Random(5)
    line = "".join(rng.choice("abcdefgh ") for _ in range(30_000))
    rows = [(1, line), (2, line[:777] + "X" + line[778:]), (3, line[:20_000]), (4, line + "ab")]
    got = {r.doc_id: (r.exact_repeats, r.near_repeats) for r in lines.line_report(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: (0, 0), 2: (0, 1), 3: (0, 0), 4: (0, 1)}
