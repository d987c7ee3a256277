import hashlib
import math
import random
import struct
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from graphcc.llm import media, mixing, neighbours, packing, quality, rollup, urlfilter
from graphcc.llm.rollup import TokenRollup, count_tokens, revised, signed
from graphcc.session import scratch_path
from tests.llm import util


def test_segment_tree_is_best_fit_decreasing():
    rng = random.Random(2)
    lengths = np.array([rng.randint(1, 64) for _ in range(500)])
    seq, off, made = packing.pack_lengths(lengths, 64)
    room, want = [], []
    for i in sorted(range(500), key=lambda i: -lengths[i]):  # the plain quadratic way
        fits = [(r, -w) for w, r in enumerate(room) if r >= lengths[i]]
        w = -min(fits)[1] if fits else len(room)
        if not fits:
            room.append(64)
        want.append(room[w])
        room[w] -= lengths[i]
    assert made == len(room)
    for w in range(made):
        mine = sorted(zip(off[seq == w], lengths[seq == w], strict=True))
        assert all(a + n == b for (a, n), (b, _) in zip(mine, mine[1:], strict=False)) and mine[0][0] == 0 and sum(mine[-1]) <= 64


def test_packing_round_trip(spark):
    texts = [None, "", "hello world", "naïve café 日本", "a <|endoftext|> b", "x  \n\n y" * 900, "  lead"] + [f"word{i} " * (i % 400) for i in range(200)]
    got = packing.pack(util.documents(spark, texts, extra=True)).collect()
    exact = packing.Tokenizer.load(packing.tokenizer_path()).exact
    by_doc, by_seq = {}, {}
    for r in got:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_seq.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for d, t in enumerate(texts):
        ids = [*exact.encode(t or "", add_special_tokens=False).ids, 1]
        at = 0
        for r in sorted(by_doc[d], key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids) and 0 < r.length <= 2048
            assert r.ids_crc32 == zlib.crc32(struct.pack(f"<{r.length}I", *ids[at : at + r.length]))
            at += r.length
        assert at == len(ids)
    for parts in by_seq.values():
        at = 0
        for off, n in sorted(parts):
            assert off == at
            at += n
        assert at <= 2048
    assert packing.pack(spark.createDataFrame([], util.SCHEMA)).count() == 0
    long_text = "some words, " * 300_000
    assert (packing.Tokenizer.load(packing.tokenizer_path()).ids(long_text) == np.array(exact.encode(long_text, add_special_tokens=False).ids)).all()


def test_png_round_trip_and_checksums():
    for text in (None, "", "a" * 64, "é" * 1000, "x y\n" * 5000):
        payload, _ = media.payload_of(text)
        stored = media.encode_png(payload)
        assert media.decode_png(stored).tobytes() == payload and len(payload) % 64 == 0 and payload
        for at in (1, 20, len(stored) // 2, len(stored) - 5):
            broken = bytearray(stored)
            broken[at] ^= 4
            with pytest.raises((ValueError, zlib.error)):
                media.decode_png(bytes(broken))


def test_png_reads_all_filters():
    img = np.random.default_rng(1).integers(0, 256, (5, 8), dtype=np.uint8)
    lines = []
    for i, kind in enumerate((0, 1, 2, 3, 4)):
        row = [kind]
        for j in range(8):
            a, b = int(img[i, j - 1]) if j else 0, int(img[i - 1, j]) if i else 0
            c = int(img[i - 1, j - 1]) if i and j else 0
            p = a + b - c
            guess = (0, a, b, (a + b) // 2, min((abs(p - a), 0, a), (abs(p - b), 1, b), (abs(p - c), 2, c))[2])[kind]
            row.append((int(img[i, j]) - guess) & 255)
        lines.append(bytes(row))
    head = struct.pack(">IIBBBBB", 8, 5, 8, 0, 0, 0, 0)
    packed = zlib.compress(b"".join(lines))
    data = media.SIGNATURE + media._chunk(b"IHDR", head) + media._chunk(b"IDAT", packed[:9]) + media._chunk(b"IDAT", packed[9:]) + media._chunk(b"IEND", b"")
    assert (media.decode_png(data) == img).all()


def test_media_features(spark):
    docs = util.documents(spark, [None, "", "same", "same", "other" * 500], extra=True)
    got = {r.doc_id: r for r in media.media_features(media.encode_texts(docs)).collect()}
    assert got[2].feature == got[3].feature and got[2].media_sha256 == got[3].media_sha256 != got[4].media_sha256
    assert got[0].payload_bytes == 64 and got[0].n_bytes == 0 and got[4].payload_bytes == 2560 and len(got[4].feature) == 16
    assert media.media_features(media.encode_texts(spark.createDataFrame([], util.SCHEMA))).count() == 0


def test_quality_learns_and_holds_out(spark):
    rng = random.Random(4)
    good, bad = ["the", "river", "stone", "walks", "slowly"], ["BUY", "now!!", "***", "cheap$$$", "click"]
    texts, labels = [], []
    for i in range(400):
        y = rng.random() < 0.6
        texts.append(" ".join(rng.choice(good if y else bad) for _ in range(rng.randint(1, 40))))
        labels.append((i, int(y)))
    docs = util.documents(spark, [*texts, None, ""], extra=True)
    held = [r.doc_id for r in docs.where(quality.bucket() == 2).collect()]
    assert {i for i in range(402) if zlib.crc32(str(i).encode()) % 4 == 2} == set(held)
    known = spark.createDataFrame([*labels, (None, 1), (5, None), labels[0]], "doc_id long, quality int")
    weights = quality.train(docs, known)
    scored = {r.doc_id: r.score for r in quality.score(docs, weights).collect()}
    assert np.mean([(scored[i] >= 0.5) == labels[i][1] for i in held if i < 400]) > 0.95 and 0 <= scored[400] == scored[401] <= 1
    flipped = spark.createDataFrame([(i, 1 - y if i in held else y) for i, y in labels], "doc_id long, quality int")
    assert (quality.train(docs, flipped) == weights).all()  # labels of the held-out fold change nothing
    assert (quality.train(docs, known.limit(0)) == 0).all()
    assert quality.score(docs.limit(0), weights).count() == 0


def test_rollup_is_idempotent_and_additive(spark):
    schema = "source string, lang string, tokenizer string, n_tokens long"
    a = spark.createDataFrame([("s", "en", "v1", 5), ("s", "en", "v1", 7), (None, "de", "v1", None)], schema)
    one = spark.createDataFrame([("s", "en", "v1", 7)], schema)
    totals = TokenRollup(spark, scratch_path(spark, "rollup"))
    see = lambda: sorted(map(tuple, totals.totals().collect()), key=str)
    assert see() == []
    assert totals.commit("a", signed(a, 1)) and not totals.commit("a", signed(a, 1))
    assert see() == sorted([("s", "en", "v1", 2, 12), (None, "de", "v1", 1, 0)], key=str)
    totals.compact()
    assert not totals.commit("a", signed(a, 1))
    totals.commit("b", revised(one, one.withColumn("tokenizer", F.lit("v2")).withColumn("n_tokens", F.lit(9).cast("long"))))
    totals.commit("empty", signed(a.limit(0), 1))
    want = sorted([("s", "en", "v1", 1, 5), ("s", "en", "v2", 1, 9), (None, "de", "v1", 1, 0)], key=str)
    assert see() == want
    totals.compact()
    totals.compact()
    assert see() == want and totals.batches() == {"a", "b", "empty"}
    totals.commit("c", signed(a.where("source IS NULL"), -1))
    assert see() == [x for x in want if x[0] is not None]


def brute_targets(sizes, weights=(5, 2, 1), cap=3.0):
    names = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    weight = {s: weights[i % 3] for i, s in enumerate(names)}
    total, fixed = float(sum(sizes.values())), {}
    while True:
        free = [s for s in names if s not in fixed]
        rest, wsum = total - sum(fixed.values()), sum(weight[s] for s in free)
        over = [s for s in free if rest * weight[s] / wsum > cap * sizes[s]] if wsum else []
        if not over:
            return fixed | {s: rest * weight[s] / wsum for s in free}
        fixed |= {s: cap * sizes[s] for s in over}


def test_mixing_targets_and_documents(spark):
    rng = random.Random(6)
    for case in range(4):
        sources = [None, "b", "a", "ü", "z", "A"][: case + 3]
        texts = [" ".join(["w"] * rng.randint(0, 30)) for _ in range(300)]
        which = [rng.choice(sources[:1] * 8 + sources) for _ in texts]
        docs = util.documents(spark, [*texts, None], sources=[*which, "a"], extra=True)
        got = mixing.plan(mixing.sizes_of(docs)).collect()
        size = {}
        for t, s in zip(texts, which, strict=True):
            size[s] = size.get(s, 0) + len(t.split())
        size.setdefault("a", 0)
        want, taken = brute_targets(size), {}
        assert len(got) == 301
        for r in got:
            assert r.source_size == size[r.source] and r.target == pytest.approx(want[r.source]) and r.taken <= 3 * r.size and r.taken == r.copies * r.size
            assert 0 <= r.position <= 1
            taken[r.source] = taken.get(r.source, 0) + r.taken
        assert all(abs(taken[s] - want[s]) <= 31 for s in taken)
        mixed = mixing.mix(docs)
        assert mixed.columns == docs.columns and mixed.count() == sum(r.copies for r in got)
        assert mixed.collect() == mixing.mix(docs).collect()


def test_mixing_is_native_and_takes_an_empty_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for df in (mixing.plan(mixing.sizes_of(docs)), mixing.mix(docs)):
        plan = df._jdf.queryExecution().toString()
        assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan
    assert mixing.mix(docs.limit(0)).count() == 0


def test_position_inverts_the_schedule(spark):
    rows = [(float(c), s) for c in range(0, 101, 5) for s in (-0.9, -0.5, 0.0, 0.5, 0.9)]
    df = spark.createDataFrame(rows, "c double, s double")
    for r in df.select("c", "s", mixing.due(F.col("c"), F.lit(100.0), F.col("s")).alias("t")).collect():
        assert 100 * (r.t + r.s * (r.t * r.t - r.t)) == pytest.approx(r.c, abs=1e-9)


def brute_nearest(rows, k, step):
    ok = {i: np.array(v, np.float64) for i, v in rows if i is not None and v is not None and len(v) == 8 and all(x is not None and np.isfinite(x) for x in v) and any(v)}
    out = {}
    for q, v in ok.items():
        if q % step == 0:
            s = sorted((-(w @ v) / np.sqrt((w @ w) * (v @ v)), i) for i, w in ok.items() if i != q)
            out[q] = [i for _, i in s[:k]]
    return out


def test_nearest_neighbours(spark):
    rng = np.random.default_rng(9)
    rows = [(i, rng.normal(size=8).astype(np.float32).tolist()) for i in range(900)]
    rows += [(1000 + i, rows[7][1]) for i in range(300)]  # a group of copies
    rows += [(2000, None), (2050, [0.0] * 8), (2100, [1.0] * 7 + [None]), (2150, [float("nan")] * 8), (2200, [1.0] * 3), (None, [1.0] * 8), (2250, [])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("leaf", F.lit("clash"))
    want = brute_nearest(rows, 5, 50)
    for options in ({}, {"group_rows": 100, "group_queries": 7}):
        got = {}
        for r in neighbours.nearest(df, F.col("vec_id") % 50 == 0, **options).orderBy("query_id", "rank").collect():
            got.setdefault(r.query_id, []).append(r)
        assert got.keys() == want.keys() and all([r.rank for r in rs] == [1, 2, 3, 4, 5] for rs in got.values())
        hits = sum(len({r.vec_id for r in got[q]} & set(w)) for q, w in want.items())
        assert hits >= 0.9 * 5 * len(want)
        copies = [r.vec_id for r in got[1000]]
        assert copies == [7, 1001, 1002, 1003, 1004]
    assert neighbours.nearest(df.limit(0), F.col("vec_id") % 50 == 0).count() == 0
    few = neighbours.nearest(df.where("vec_id in (0, 1, 2)"), F.col("vec_id") % 50 == 0).collect()
    assert [r.rank for r in few] == [1, 2]


def test_nearest_neighbours_are_k_where_leaves_are_small(spark):
    rng = np.random.default_rng(4)
    rows = [(i, rng.normal(size=8).astype(np.float32).tolist()) for i in range(300)] + [(0, [1.0] * 8)] * 6
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = neighbours.nearest(df, F.col("vec_id") % 50 == 0, recall=0.01).groupBy("query_id").agg(F.max("rank").alias("n")).collect()
    assert {r.query_id: r.n for r in got} == {q: 5 for q in range(0, 300, 50)}


def test_url_rules(spark):
    urls = ["http://A.example.com/en/1", "https://www.example.com/en/1?x", "http://example.com/fr/", "http://x.net/es/a#b", "net://net/fr/", "http://badnet/es/", "no url", None, "", "http://", "http://Q.ORG", "://com/?a", "http://EXAMPLE.com/EN/"]
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urlfilter.judge_urls(spark, pages).collect()}
    assert got[0] == ("a.example.com", "/en/1", "example.com/en/", "block") and got[1] == ("www.example.com", "/en/1", "www.example.com/en/", "allow")
    assert got[2][2:] == ("com/", "allow") and got[3] == ("x.net", "/es/a", "net/es/", "block") and got[4][2:] == ("net/fr/", "block")
    assert got[5] == ("badnet", "/es/", None, "allow") and got[6] == ("", "", None, "allow") == got[7] == got[8] == got[9]
    assert got[10] == ("q.org", "", None, "allow") and got[11] == ("com", "/", "com/", "allow") and got[12] == ("example.com", "/EN/", "com/", "allow")
    assert urlfilter.judge_urls(spark, pages.limit(0)).count() == 0


def test_equal_digests_are_told_apart_by_strings(tmp_path, monkeypatch):
    monkeypatch.setattr(urlfilter.xxhash, "xxh64_intdigest", lambda s: len(s))
    urlfilter.write_rules([("aa", "/", "block"), ("bb", "/", "allow")], str(tmp_path / "rules"))
    array = urlfilter.DigestArray(str(tmp_path / "rules"))
    found = array.find([b"aa/", b"bb/", b"cc/", b"longer"])
    assert [array.string(i) if i >= 0 else None for i in found] == [b"aa/", b"bb/", None, None]


def test_mix_has_the_shares_of_the_schedule(spark):
    """Equal spans of positions hold equal words, and each source its normalised weight's share of them."""
    docs = spark.range(9000).selectExpr("id AS doc_id", "element_at(array('a', 'b', 'c'), CAST(id % 3 AS INT) + 1) AS source", "'w x' AS text")
    rows = mixing.plan(mixing.sizes_of(docs), weights=(2, 1, 1)).collect()
    due, drift, placed = {r.source: (r.target, r.slope) for r in rows}, rows[0].drift, []
    total = sum(d for d, _ in due.values())
    assert drift == pytest.approx(sum(d * s for d, s in due.values()) / total) != 0
    for r in rows:
        for c in range(r.copies):
            lo, hi = 0.0, 1.0  # the time at which the integrated weight reaches what came before this copy
            for _ in range(50):
                t = (lo + hi) / 2
                lo, hi = (t, hi) if r.target * (t + r.slope * (t * t - t)) < r.before + c * r.source_size else (lo, t)
            placed.append((r.source, t, t + drift * (t * t - t)))
            assert c or r.position == pytest.approx(placed[-1][2], abs=1e-6)
    for lo in (0.0, 0.25, 0.5, 0.75):
        inside = [(s, t) for s, t, p in placed if lo <= p < lo + 0.25]
        assert len(inside) == pytest.approx(len(placed) / 4, rel=0.02)
        mid = np.mean([t for _, t in inside])
        weight = {s: d * (1 + e * (2 * mid - 1)) for s, (d, e) in due.items()}
        for s, w in weight.items():
            assert sum(x == s for x, _ in inside) / len(inside) == pytest.approx(w / sum(weight.values()), abs=0.02)


def test_commits_during_compaction_count_once(spark, monkeypatch):
    change = spark.createDataFrame([("s", "en", "v1", 5)], "source string, lang string, tokenizer string, n_tokens long")
    totals = TokenRollup(spark, scratch_path(spark, "rollup"))
    totals.commit("a", signed(change, 1))
    rename = totals._rename

    def busy(a, b):
        rename(a, b)
        totals.commit("b", signed(change, 1))

    monkeypatch.setattr(totals, "_rename", busy)
    totals.compact()
    assert [tuple(r) for r in totals.totals().collect()] == [("s", "en", "v1", 2, 10)] and totals.batches() == {"a", "b"}


def test_token_counts_by_public_vocabularies(spark):
    import tokenizers

    texts = [None, "", "Hello world, it's 2024!", "naïve café — ß", "x" * 3000, "one two " * 300, "日本語 текст"]
    docs = util.documents(spark, texts, extra=True)
    docs = docs.union(docs.where("doc_id = 2"))
    exact = tokenizers.Tokenizer.from_file(packing.tokenizer_path("byte_bpe_50k.json"))
    got = count_tokens(docs, "byte_bpe_50k").collect()
    assert sorted(r.n_tokens for r in got if r.doc_id == 2) == [len(exact.encode(texts[2]).ids)] * 2
    assert {r.doc_id: r.n_tokens for r in got} == {i: len(exact.encode(t or "", add_special_tokens=False).ids) for i, t in enumerate(texts)}
    other = {r.doc_id: r.n_tokens for r in count_tokens(docs, "byte_bpe_multi_50k").collect()}
    assert other[0] == other[1] == 0 and other != {r.doc_id: r.n_tokens for r in got}


def test_token_rollup_query_against_direct_counts(spark, sf):
    from graphcc.llm import queries

    toxic = {r.doc_id for r in spark.read.parquet(f"{sf}/labels.parquet").where("toxic = 1").collect()}
    docs = [r for r in spark.read.parquet(f"{sf}/documents.parquet").collect() if r.doc_id not in toxic]
    count = {v: rollup._counter(rollup.vocabulary_path(v)) for v in queries.VERSIONS}
    want = {}
    for r in docs:
        version = queries.VERSIONS[r.lang in queries.RECOUNTED]
        d, n = want.get((r.source, r.lang, version), (0, 0))
        want[r.source, r.lang, version] = d + 1, n + count[version](r.text or "")
    got = {(r.source, r.lang, r.tokenizer): (r.documents, r.tokens) for r in queries.op2_token_rollup(spark, sf).collect()}
    assert got == want


def direct_hash(img):
    """Box means over 32 x 32 by fine repetition, then the cosine sums as they are defined."""
    h, w = img.shape
    small = img.astype(float).repeat(32, 0).reshape(32, h, w).mean(1).T.repeat(32, 0).reshape(32, w, 32).mean(1).T
    low = [sum(small[y, x] * np.cos(np.pi * (2 * y + 1) * i / 64) * np.cos(np.pi * (2 * x + 1) * j / 64) for y in range(32) for x in range(32)) for i in range(8) for j in range(8)]
    low = np.round(low, 4)
    return np.packbits(low > np.median(low[1:])).tobytes().hex()


def test_media_features_against_direct_computation(spark):
    texts = [None, "", "a" * 64, "é" * 100, "some words\nand more " * 40, "z" * 200_000]
    docs = util.documents(spark, texts, extra=True)
    stored = {r.doc_id: bytes(r.media) for r in media.encode_texts(docs).collect()}
    for r in media.media_features(media.encode_texts(docs)).collect():
        raw = (texts[r.doc_id] or "").encode()
        padded = raw + bytes(-len(raw) % 64) if raw else bytes(64)
        img = np.frombuffer(padded, np.uint8).reshape(-1, 64)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-64:]))
        assert (r.media_bytes, r.media_sha256) == (len(stored[r.doc_id]), hashlib.sha256(stored[r.doc_id]).hexdigest())
        if len(padded) < 5000:
            assert r.feature == direct_hash(img)


def test_png_diagonals_against_one_by_one():
    rng = np.random.default_rng(3)
    for height, width in ((1, 1), (1, 9), (40, 3), (3, 64), (70, 64)):
        rows, kinds = rng.integers(0, 256, (height, width), dtype=np.uint8), rng.integers(0, 5, height).astype(np.uint8)
        want = np.zeros_like(rows)
        for i in range(height):
            for j in range(width):
                a, b, c = (int(want[i, j - 1]) if j else 0), (int(want[i - 1, j]) if i else 0), (int(want[i - 1, j - 1]) if i and j else 0)
                p = a + b - c
                near = min(((abs(p - a), 0, a), (abs(p - b), 1, b), (abs(p - c), 2, c)))[2]
                want[i, j] = (int(rows[i, j]) + (0, a, b, (a + b) // 2, near)[kinds[i]]) & 255
        assert (media._unfilter(kinds, rows) == want).all()


def test_quality_updates_and_scores_against_plain_python(spark):
    """Two documents, one pass at a time: the published per-coordinate update, coordinate by coordinate."""
    rng = np.random.default_rng(2)
    examples = [(np.array(sorted(rng.choice(30, 6, replace=False))), int(y)) for y in rng.integers(0, 2, 40)]
    model, z, n, bias = quality.Ftrl(31), [0.0] * 31, [0.0] * 31, 30
    alpha, beta, l1, l2 = model.alpha, model.beta, model.l1, model.l2
    weight = lambda i: 0.0 if abs(z[i]) <= l1 else -(z[i] - math.copysign(l1, z[i])) / ((beta + math.sqrt(n[i])) / alpha + l2)
    for at, y in examples:
        model.learn(at, 1 / math.sqrt(len(at)), y, bias)
        value = {int(i): 1 / math.sqrt(len(at)) for i in at} | {bias: 1.0}
        w = {i: weight(i) for i in value}
        p = 1 / (1 + math.exp(-sum(w[i] * v for i, v in value.items())))
        for i, v in value.items():
            g = (p - y) * v
            z[i] += g - (math.sqrt(n[i] + g * g) - math.sqrt(n[i])) / alpha * w[i]
            n[i] += g * g
    assert np.allclose(model.weights(), [weight(i) for i in range(31)])
    docs = util.documents(spark, ["red fox", "red fox", None, "word " * 60_000], extra=True)
    weights = np.zeros((1 << quality.BITS) + 1, "<f4")
    idx, at = quality.features(pa.array(["red fox"]))
    weights[idx], weights[-1] = 0.5, 0.25
    got = {r.doc_id: r.score for r in quality.score(docs, weights).collect()}
    want = 1 / (1 + math.exp(-(0.5 * len(idx) / math.sqrt(len(idx)) + 0.25)))
    assert got[0] == got[1] == pytest.approx(want, abs=1e-8) and got[2] == pytest.approx(1 / (1 + math.exp(-0.25)), abs=1e-8) and 0 <= got[3] <= 1
    kept = quality.score(docs, weights, into="__score")
    assert {r.score for r in kept.collect()} == {"clash"}


def test_packing_keeps_repeated_rows(spark):
    docs = util.documents(spark, ["a b c", "a b c", None])
    docs = docs.union(docs)
    got = packing.pack(docs).collect()
    assert len(got) == 6 and sorted(r.doc_id for r in got) == [0, 0, 1, 1, 2, 2] and len({(r.sequence_id, r.offset) for r in got}) == 6


def test_nearest_neighbours_of_other_lengths_and_repeated_ids(spark):
    rng = np.random.default_rng(12)
    rows = [(i, rng.normal(size=8).astype(np.float32).tolist()) for i in range(120)] + [(1000 + i, rng.normal(size=3).astype(np.float32).tolist()) for i in range(60)]
    rows += [(i, rows[0][1]) for i in (0, 0, 3000, 3000)]  # ids given to several rows
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = {}
    for r in neighbours.nearest(df, F.col("vec_id") % 50 == 0, recall=1.0).collect():
        got.setdefault(r.query_id, []).append(r.vec_id)
    assert all(len(v) == 5 for v in got.values()) and set(got) == {0, 50, 100, 1000, 1050, 3000}
    assert all((v >= 1000) == (q in (1000, 1050)) for q in (50, 100, 1000, 1050) for v in got[q] if v != 3000)
    assert got[0][:2] == [3000, 3000] and 0 not in got[0] and got[3000][:3] == [0, 0, 0]


def test_cells_hold_neighbouring_leaves():
    cell, blocks = neighbours.cells_of(np.array([3, 4, 50, 2, 0, 9]), 10)
    assert cell.tolist() == [0, 0, 1, 2, 2, 3] and blocks.tolist() == [1, 5, 1, 1]
    ids, x = np.array([9, 4, 7, 1]), np.array([[1, 2], [1, 2], [1, 2], [3, 4]], np.float32)
    assert neighbours._smallest_of_equals(ids, x, 2).tolist() == [False, True, True, True]


def test_urls_of_any_length(spark):
    long = "http://" + "a." * 200_000 + "net/es/" + "x" * 100_000
    rows = [(1, long), (1, long), (None, "http://b.example.com/en/"), (2, "http://" + "a" * 300_000)]
    got = urlfilter.judge_urls(spark, spark.createDataFrame(rows, "page_id long, url string")).collect()
    assert [(r.page_id, r.rule, r.verdict) for r in got] == [(1, "net/es/", "block")] * 2 + [(None, "example.com/en/", "block"), (2, None, "allow")]
