"""The registered queries of this subpackage, and their SQL for DuckDB."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphcc.llm.tables import WORD, n_words, table
from graphcc.session import keep, scratch_path


def op1_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphcc.llm.jaccard import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"), k=4, percent=85)


def _components_of(links: str) -> str:
    """DuckDB text for ``(node, component)`` of links (u, v), read in both directions."""
    return f"""cc(node, component) USING KEY (node) AS (SELECT u, min(least(u, v)) FROM {links} GROUP BY u
  UNION SELECT s.v, min(cc.component) FROM cc JOIN {links} s ON s.u = cc.node JOIN recurring.cc r ON r.node = s.v WHERE cc.component < r.component GROUP BY s.v)"""


#: Shingles are strings here, sets are told apart by digest, and documents (by doc_id) and sets are nodes of one graph.
OP1_SQL = f"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{WORD}') AS ws FROM documents),
g AS (SELECT doc_id, CASE WHEN len(ws) >= 4 THEN list_sort(list_distinct(list_transform(range(1, len(ws) - 2), lambda i: array_to_string(ws[i:i + 3], ' '))))
    WHEN len(ws) > 0 THEN [array_to_string(ws, ' ')] ELSE [] END AS s FROM w),
d AS (SELECT doc_id, len(s)::BIGINT AS n, s, CASE WHEN len(s) > 0 THEN md5(array_to_string(s, chr(10))) END AS h FROM g),
c AS (SELECT row_number() OVER (ORDER BY h) AS c, h, any_value(n) AS n, any_value(s) AS s FROM d WHERE h IS NOT NULL GROUP BY h),
p AS (SELECT c, n, unnest(s) AS t FROM c),
m AS (SELECT a.c AS a, b.c AS b FROM p a JOIN p b ON a.t = b.t AND a.c < b.c AND 100 * least(a.n, b.n) >= 85 * greatest(a.n, b.n)
  GROUP BY a.c, b.c, a.n, b.n HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))),
ids AS (SELECT dense_rank() OVER (ORDER BY doc_id) + 1000000000 AS i, doc_id, h FROM d WHERE doc_id IS NOT NULL),
l AS (SELECT a AS u, b AS v FROM m UNION SELECT i, c FROM ids JOIN c USING (h)),
e AS (SELECT u, v FROM l UNION SELECT v, u FROM l),
{_components_of("e")},
x AS (SELECT component, min(doc_id) AS label FROM ids JOIN cc ON cc.node = ids.i GROUP BY component),
of_class AS (SELECT h, label FROM c JOIN cc ON cc.node = c.c JOIN x USING (component)),
of_doc AS (SELECT DISTINCT doc_id, label FROM ids JOIN cc ON cc.node = ids.i JOIN x USING (component))
SELECT d.doc_id, d.n AS n_shingles, coalesce(k.label, o.label, d.doc_id) AS component_id
FROM d LEFT JOIN of_class k ON k.h = d.h LEFT JOIN of_doc o ON o.doc_id = d.doc_id
"""


#: Tokenizer versions of the rollup: what documents are counted by at first, and what two languages are recounted by.
VERSIONS, RECOUNTED = ("byte_bpe_50k", "byte_bpe_multi_50k"), ("de", "fr")


def _rolled_up(spark: SparkSession, first: DataFrame, second: DataFrame, labels: DataFrame) -> DataFrame:
    """Totals after four commits: all documents in, toxic ones out, two languages recounted, one replay."""
    from graphcc.llm.rollup import TokenRollup, revised, signed

    toxic = labels.where("toxic = 1").select("doc_id").distinct()
    left = lambda df: df.join(toxic, "doc_id", "left_anti").where(F.col("lang").isin(*RECOUNTED))
    totals = TokenRollup(spark, scratch_path(spark, "rollup"))
    totals.commit("0001-load", signed(first, 1))
    totals.commit("0002-toxic", signed(first.join(toxic, "doc_id", "left_semi"), -1))
    totals.compact()
    recount = revised(left(first), left(second))
    totals.commit("0003-recount", recount)
    totals.commit("0003-recount", recount)
    return totals.totals()


def op2_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens by two public vocabularies, kept up to date by signed commits."""
    from graphcc.llm.rollup import count_tokens

    docs = table(spark, sf_dir, "documents", "doc_id", "source", "lang", "text")
    first = keep(count_tokens(docs, VERSIONS[0]), "counts")
    second = keep(count_tokens(docs.where(F.col("lang").isin(*RECOUNTED)), VERSIONS[1]), "counts")
    return _rolled_up(spark, first, second, table(spark, sf_dir, "labels"))


def op2_token_rollup_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same commits over counts that SQL can make too: words, and words and signs."""
    docs = table(spark, sf_dir, "documents", "doc_id", "source", "lang", "text")
    pieces = F.coalesce(F.regexp_count("text", F.lit(PIECE)), F.lit(0)).cast("long")
    counted = keep(docs.select("doc_id", "source", "lang", n_words(F.col("text")).alias("words"), F.when(F.col("lang").isin(*RECOUNTED), pieces).alias("pieces")), "counts")
    by = lambda name, col: counted.select("doc_id", "source", "lang", F.lit(name).alias("tokenizer"), F.col(col).alias("n_tokens"))
    return _rolled_up(spark, by("words-1", "words"), by("pieces-2", "pieces"), table(spark, sf_dir, "labels"))


#: Words and single ASCII signs.
PIECE = r"[!-/:-@\[-`{-~]|[^\x20\x09-\x0D!-/:-@\[-`{-~]+"

OP2_WORDS_SQL = f"""
WITH c AS (SELECT doc_id, source, lang,
    coalesce(len(regexp_extract_all(text, '{WORD}')), 0) AS words,
    coalesce(len(regexp_extract_all(text, '{PIECE}')), 0) AS pieces
  FROM documents WHERE doc_id IS NULL OR doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1 AND doc_id IS NOT NULL)),
t AS (SELECT source, lang, CASE WHEN lang IN ('de', 'fr') THEN 'pieces-2' ELSE 'words-1' END AS tokenizer,
    CASE WHEN lang IN ('de', 'fr') THEN pieces ELSE words END AS n FROM c)
SELECT source, lang, tokenizer, count(*)::BIGINT AS documents, sum(n)::BIGINT AS tokens FROM t GROUP BY ALL
"""


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphcc.llm.packing import pack

    return pack(table(spark, sf_dir, "documents", "doc_id", "text"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphcc.llm.lines import line_report

    return line_report(table(spark, sf_dir, "documents", "doc_id", "text"))


def op4_line_dedup_short(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Short lines too: exact repeats of any length, one edit from six characters on."""
    from graphcc.llm.lines import line_report

    return line_report(table(spark, sf_dir, "documents", "doc_id", "text"), short=True)


OP4_SQL = """
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
o AS (SELECT doc_id, unnest(ls) AS line, generate_subscripts(ls, 1) AS line_no FROM d),
k AS (SELECT * FROM o WHERE length(line) >= 6 AND trim(line) <> ''),
f AS (SELECT line, min((doc_id, line_no)) AS place, length(line) AS len, list_transform(['e', 'n', 't', 'h', 'a', 'r', 'o', 'i'], lambda c: length(line) - length(replace(line, c, ''))) AS c FROM k GROUP BY line),
n AS (SELECT DISTINCT CASE WHEN a.place > b.place THEN a.line ELSE b.line END AS line
  FROM (SELECT *, unnest([len, len - 1, len - 2]) AS want FROM f WHERE len >= 32) a JOIN f b ON a.want = b.len AND b.len >= 32 AND (a.len > b.len OR a.line < b.line)
  WHERE list_sum(list_transform(list_zip(a.c, b.c), lambda x: abs(x[1] - x[2]))) <= 4 AND levenshtein(a.line, b.line) <= 2),
r AS (SELECT k.doc_id, length(k.line) AS len, n.line IS NOT NULL AS near FROM k JOIN f USING (line) LEFT JOIN n ON n.line = k.line
  WHERE n.line IS NOT NULL OR (k.doc_id, k.line_no) <> f.place),
s AS (SELECT doc_id, sum((NOT near)::INT) AS exact, sum(near::INT) AS nearly, sum(len) AS chars FROM r GROUP BY doc_id)
SELECT d.doc_id, len(d.ls)::BIGINT AS n_lines, coalesce(exact, 0)::BIGINT AS exact_repeats, coalesce(nearly, 0)::BIGINT AS near_repeats,
  (length(d.text) - len(d.ls) + 1 - coalesce(chars, 0))::BIGINT AS kept_chars FROM d LEFT JOIN s ON d.doc_id IS NOT DISTINCT FROM s.doc_id
"""


def op5_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphcc.llm.media import encode_texts, media_features

    return media_features(encode_texts(table(spark, sf_dir, "documents", "doc_id", "text")))


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphcc.llm.quality import bucket, score, train

    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    scored = score(docs, train(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", F.coalesce(bucket() == 2, F.lit(False)).alias("held_out"), "score", F.when(F.col("score") >= 0.7, 1).otherwise(0).alias("predicted"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphcc.llm.mixing import plan, sizes_of

    planned = plan(keep(sizes_of(table(spark, sf_dir, "documents", "doc_id", "source", "text")), "sizes"))
    ordered = planned.repartitionByRange("position", "doc_id").sortWithinPartitions("position", "doc_id")
    return ordered.select("doc_id", "size", "source_size", "target", "taken", "copies", F.round("position", 9).alias("position"))


OP7_SQL = f"""
WITH d AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '{WORD}')), 0)::BIGINT AS size,
    md5(coalesce(doc_id::VARCHAR, 'null')) AS k FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
r AS (SELECT *, row_number() OVER (ORDER BY source ASC NULLS LAST) AS rk FROM s),
w AS (SELECT *, [5.0, 2.0, 1.0][((rk - 1) % 3 + 1)::INT]::DOUBLE AS weight FROM r),
q AS (SELECT *, 3.0::DOUBLE * source_size / weight AS ratio FROM w),
l AS (SELECT *, (sum(source_size) OVER () - 3.0::DOUBLE * coalesce(sum(source_size) OVER (ORDER BY ratio, rk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
    / sum(weight) OVER (ORDER BY ratio, rk ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM q),
g AS (SELECT source, source_size, [-0.5, 0.0, 0.5][((rk - 1) % 3 + 1)::INT]::DOUBLE AS slope, least(weight * coalesce((SELECT level FROM l WHERE level <= ratio ORDER BY ratio, rk LIMIT 1), 0), 3.0::DOUBLE * source_size) AS target FROM l),
t AS (SELECT *, coalesce(sum(target * slope) OVER () / nullif(sum(target) OVER (), 0), 0) AS drift FROM g),
c AS (SELECT d.doc_id, d.size, t.source_size, t.target, t.slope, t.drift,
    sum(d.size) OVER (PARTITION BY d.source ORDER BY substr(d.k, 1, 3), d.k, d.size ROWS UNBOUNDED PRECEDING) - d.size AS before,
    CASE WHEN t.source_size > 0 THEN floor(t.target / t.source_size) ELSE 0 END AS whole
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
n AS (SELECT *, least(whole + CASE WHEN before + size / 2.0::DOUBLE < target - whole * source_size THEN 1 ELSE 0 END, 3)::BIGINT AS copies,
    CASE WHEN target > 0 THEN least(before / target, 1.0::DOUBLE) ELSE 0 END AS share FROM c),
y AS (SELECT *, CASE WHEN share > 0 THEN least(2 * share / ((1 - slope) + sqrt((1 - slope) * (1 - slope) + 4 * slope * share)), 1.0::DOUBLE) ELSE 0 END AS due FROM n)
SELECT doc_id, size, source_size, target, (copies * size)::BIGINT AS taken, copies, round(due + drift * (due * due - due), 9)::DOUBLE AS position FROM y
"""


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphcc.llm.substrings import dedup_substrings

    return dedup_substrings(table(spark, sf_dir, "documents", "doc_id", "text"))


OP8_SQL = f"""
WITH w AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(coalesce(text, ''), '{WORD}') AS ws FROM documents),
x AS (SELECT r, unnest(range(1, len(ws) - 33)) AS a, ws FROM w WHERE len(ws) >= 35),
s AS (SELECT r, a, md5(array_to_string(ws[a:a + 34], ' ')) AS h FROM x),
t AS (SELECT h FROM s GROUP BY h HAVING count(*) > 1),
c AS (SELECT DISTINCT r, unnest(range(a, a + 35)) AS i FROM s JOIN t USING (h)),
o AS (SELECT r, list(i) AS gone FROM c GROUP BY r),
k AS (SELECT doc_id, ws, coalesce(gone, []) AS gone FROM w LEFT JOIN o USING (r))
SELECT doc_id, len(ws)::BIGINT AS n_words, len(gone)::BIGINT AS n_removed,
  sha256(coalesce(array_to_string(list_filter(ws, lambda v, i: NOT list_contains(gone, i)), ' '), '')) AS kept_sha256 FROM k
"""


def op9_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphcc.llm.neighbours import nearest

    return nearest(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), F.col("vec_id") % 50 == 0)


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphcc.llm.urlfilter import judge_urls

    return judge_urls(spark, table(spark, sf_dir, "pages", "page_id", "url"))


OP10_SQL = r"""
WITH rules(rhost, rpath, verdict) AS (VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'),
    ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
u AS (SELECT row_number() OVER () AS n, page_id, CASE WHEN position('://' IN url) > 0 THEN regexp_extract(substr(url, position('://' IN url) + 3), '^[^?#]*') ELSE '' END AS rest FROM pages),
h AS (SELECT n, page_id, translate(regexp_extract(rest, '^[^/]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    CASE WHEN position('/' IN rest) > 0 THEN substr(rest, position('/' IN rest)) ELSE '' END AS path FROM u),
f AS (SELECT n, arg_max(rhost || rpath, length(rhost || rpath)) AS rule, arg_max(verdict, length(rhost || rpath)) AS verdict
  FROM h JOIN rules ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath) GROUP BY n)
SELECT page_id, host, path, rule, coalesce(f.verdict, 'allow') AS verdict FROM h LEFT JOIN f USING (n)
"""

QUERIES = {
    f.__name__: f
    for f in (
        op1_jaccard_join, op2_token_rollup, op3_packing, op4_line_dedup, op5_media_columns, op6_quality_classifier, op7_mixing, op8_substring_dedup,
        op9_nearest_neighbours, op10_url_filter, op4_line_dedup_short, op2_token_rollup_words,
    )
}
ORACLES = {
    "op1_jaccard_join": OP1_SQL, "op2_token_rollup_words": OP2_WORDS_SQL, "op4_line_dedup": OP4_SQL, "op7_mixing": OP7_SQL, "op8_substring_dedup": OP8_SQL,
    "op10_url_filter": OP10_SQL,
}
