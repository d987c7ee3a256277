"""Every stage of the pipeline against a brute-force twin on its own input."""

import collections

import duckdb
import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from graphcc.llm import lines, packing  # noqa: E402
from graphcc.llm.queries import OP7_SQL  # noqa: E402
from graphcc.session import Kept  # noqa: E402
from tests.llm import util  # noqa: E402


def within_two(a, b):
    """Whether two strings are within two edits: a dynamic programme over the five middle diagonals."""
    if abs(len(a) - len(b)) > 2:
        return False
    row = {j: j for j in range(3)}
    for i in range(1, len(a) + 1):
        new = {}
        for j in range(max(0, i - 2), min(len(b), i + 2) + 1):
            best = 9
            if j:
                best = min(best, row.get(j - 1, 9) + (a[i - 1] != b[j - 1]), new.get(j - 1, 9) + 1)
            new[j] = min(best, row.get(j, 9) + 1)
        row = new
        if min(row.values()) > 2:
            return False
    return row.get(len(b), 9) <= 2


def brute_lines(rows):
    first, occurrences = {}, []
    for d, t in sorted(rows):
        for i, x in enumerate((t or "").split("\n")):
            if len(x) >= lines.EXACT_CHARS and x.strip(" "):
                first.setdefault(x, (d, i))
                occurrences.append((d, i, x))
    by_length = collections.defaultdict(list)
    for x in first:
        by_length[len(x)].append(x)
    near = {x for x in first if len(x) >= 32 and any(first[y] < first[x] and within_two(x, y) for n in range(max(32, len(x) - 2), len(x) + 3) for y in by_length[n] if y != x)}
    gone = {(d, i) for d, i, x in occurrences if x in near or first[x] != (d, i)}
    out = {}
    for d, t in rows:
        parts = (t or "").split("\n")
        kept = [x for i, x in enumerate(parts) if (d, i) not in gone]
        if len(kept) == len(parts):
            out[d] = t
        elif "\n".join(kept).strip(" \n\r\t"):
            out[d] = "\n".join(kept)
    return out


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    odd = spark.createDataFrame([(10_001, None, None, None, None), (10_002, "", "en", "src0", 0)], docs.schema)
    docs = Kept(docs.unionByName(odd), "docs").df
    columns = docs.columns
    stage = dict(corpus_pipeline.STAGES)

    good = Kept(stage["quality classifier"](spark, docs, sf), "good").df
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    ids = {r.doc_id for r in good.select("doc_id").collect()}
    assert good.columns == columns and good.subtract(docs).count() == 0
    kept = [labels[i] for i in ids if i in labels]
    assert sum(kept) >= 0.97 * sum(v for v in labels.values()) and len(ids) < docs.count() and {10_001, 10_002} <= ids

    plain = Kept(stage["line dedup"](spark, good, sf), "plain").df
    want = brute_lines([(r.doc_id, r.text) for r in good.collect()])
    got = plain.collect()
    assert plain.columns == columns and {r.doc_id: r.text for r in got} == want and len(got) == len(want)
    assert all(r.n_chars == len(r.text) for r in got if r.text)

    unique = Kept(stage["n-gram Jaccard join"](spark, plain, sf), "unique").df
    component = util.jaccard_components([(r.doc_id, r.text) for r in got], 5, 80)
    assert {r.doc_id for r in unique.collect()} == {d for d, c in component.items() if d == c} and unique.columns == columns

    mixed = Kept(stage["mixing"](spark, unique, sf), "mixed").df
    duck = duckdb.connect()
    duck.register("documents", unique.toPandas())
    copies = {r[0]: r[1] for r in duck.sql(f"SELECT doc_id, copies FROM ({OP7_SQL})").fetchall()}
    assert mixed.columns == columns and collections.Counter(r.doc_id for r in mixed.collect()) == {d: c for d, c in copies.items() if c}
    assert mixed.exceptAll(mixed.intersect(unique)).count() == mixed.count() - mixed.distinct().count()

    packed = stage["packing"](spark, mixed, sf).collect()
    tok = packing.Tokenizer.load(packing.tokenizer_path())
    tokens = sum(len(tok.exact.encode(r.text or "", add_special_tokens=False).ids) + 1 for r in mixed.collect())
    assert sum(r.length for r in packed) == tokens and max(r.offset + r.length for r in packed) <= 2048


def test_quality_stage_drops_bad_documents(spark):
    sf = "/root/testdata/sf0.1"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    held = spark.read.parquet(f"{sf}/labels.parquet").where("quality IS NOT NULL AND pmod(crc32(CAST(CAST(doc_id AS STRING) AS BINARY)), 4) = 2")
    left = corpus_pipeline.quality_filter(spark, docs, sf).select("doc_id")
    bad, good = (held.where(f"quality = {q}").select("doc_id").distinct() for q in (0, 1))
    assert bad.join(left, "doc_id", "left_semi").count() <= 0.3 * bad.count()
    assert good.join(left, "doc_id", "left_anti").count() <= 0.01 * good.count()


def test_near_duplicates_keep_one_of_repeated_rows(spark):
    docs = util.documents(spark, ["a b c d e f g"] * 3 + [None, "", "other words in this one here"])
    docs = docs.union(docs.where("doc_id = 5")).union(docs.where("doc_id = 5"))
    left = corpus_pipeline.near_duplicates(spark, docs, "")
    assert sorted(r.doc_id for r in left.collect()) == [0, 3, 4, 5]


def test_run_and_empty_input(spark, sf, tmp_path):
    out = corpus_pipeline.run(spark, sf)
    assert out.columns == [c.split()[0] for c in packing.SCHEMA.split(", ")] and out.count() > 100
    for name in ("documents", "labels"):
        spark.read.parquet(f"{sf}/{name}.parquet").limit(0).write.parquet(str(tmp_path / f"{name}.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_stage_names_follow_the_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality classifier", "line dedup", "n-gram Jaccard join", "mixing", "packing"]


def test_rows_that_share_an_id_stay_unless_alike(spark):
    rows = [(7, "one two three four five six seven"), (7, "quite another text of so many words"), (7, "one two three four five six seven"), (None, "a third one that has no id at all"), (None, "and a fourth that has none as well")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'en' AS lang", "'s' AS source", "1L AS n_chars")
    left = corpus_pipeline.near_duplicates(spark, docs, "")
    assert sorted(r.text for r in left.collect()) == sorted({t for _, t in rows})


def test_stages_leave_columns_of_any_name_alone(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(30).selectExpr("*", "'mine' AS score", "doc_id AS position", "7 AS component_id", "text AS line")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before, docs = docs, Kept(stage(spark, docs, sf), "stage").df
        assert docs.columns == before.columns, name
    assert docs.where("score <> 'mine' OR position <> doc_id OR component_id <> 7").count() == 0 and docs.count()
