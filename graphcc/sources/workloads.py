"""Edge builders over the given tables, each in one SQL text that Spark and DuckDB both run.

``{table}`` stands for a table and ``{unnest}``, ``{lines}``, ``{json_k}``, ``{cosine}`` for the few
functions the dialects name differently. Kinds of nodes are kept apart by 2 * id and 2 * id + 1.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphcc.functions.ids import dictionary
from graphcc.operators.joins import cosine_join, cosine_links

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

_LINES = "(SELECT doc_id, md5(line) AS h FROM (SELECT doc_id, {unnest}({lines}) AS line FROM {documents}) x WHERE length(trim(line)) >= 20)"
_HREFS = "(SELECT page_id, {unnest}(regexp_extract_all(html, 'href=\"([^\"#]+)\"', 1)) AS href FROM {pages})"
_HOSTS = "(SELECT page_id, regexp_extract(url, '://([^/?#]+)', 1) AS host FROM {pages})"


def _dictionary(source: str, value: str) -> str:
    # Grouping by the first characters keeps the numbering distributed: ranks inside a prefix, plus the values before it.
    return f"""(SELECT s, CAST(before + row_number() OVER (PARTITION BY p ORDER BY s) - 1 AS BIGINT) AS id FROM
        (SELECT DISTINCT {value} AS s, substr({value}, 1, 3) AS p FROM {source} z) v
        JOIN (SELECT pp, sum(n) OVER (ORDER BY pp) - n AS before FROM (SELECT substr(s, 1, 3) AS pp, count(*) AS n FROM (SELECT DISTINCT {value} AS s FROM {source} z) y GROUP BY 1) c) b ON v.p = b.pp)"""


def scrambled(id_: str) -> str:
    """Ids in no useful order: each million or so is permuted in itself, so that no two become equal."""
    return f"({id_} - {id_} % 1000003 + {id_} % 1000003 * 7919 % 1000003)"


def turn_id(conversation: str = "conv_id", turn: str = "turn") -> str:
    """One number for a turn of a conversation, of up to ten million turns."""
    return f"({conversation} * 10000000 + {turn})"


_NEXT = "lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id)"
# The next event over all users, one day per window; days are tied by their first and last events.
_OVERALL = """(SELECT event_id AS u, lead(event_id) OVER (PARTITION BY date_trunc('day', ts) ORDER BY ts, event_id) AS v FROM {events}
    UNION ALL
    SELECT last_id, lead(first_id) OVER (ORDER BY day) FROM (SELECT date_trunc('day', ts) AS day, min_by(event_id, ts) AS first_id, max_by(event_id, ts) AS last_id
        FROM {events} GROUP BY 1) days)"""

LEAST_COSINE = 0.4

EDGES = {
    "w1": "SELECT o_custkey * 2 AS u, o_orderkey * 2 + 1 AS v FROM {orders}",
    "w2": "SELECT DISTINCT l_orderkey * 2 AS u, l_partkey * 2 + 1 AS v FROM {lineitem} WHERE l_quantity = 50",
    "w2b": "SELECT DISTINCT l_orderkey * 2 AS u, l_partkey * 2 + 1 AS v FROM {lineitem} WHERE l_quantity >= 47",
    "w3": "SELECT l_orderkey * 2 AS u, l_partkey * 2 + 1 AS v FROM {lineitem}",
    "w4": "SELECT l_partkey * 2 AS u, l_suppkey * 2 + 1 AS v FROM {lineitem}",
    "w5": "SELECT a.vec_id AS u, b.vec_id AS v FROM {embeddings} a JOIN {embeddings} b ON a.label = b.label AND a.vec_id < b.vec_id",
    "w6": f"SELECT u, v FROM (SELECT event_id AS u, {_NEXT} AS v FROM {{events}}) x WHERE v IS NOT NULL",
    "w6b": f"SELECT u, v FROM (SELECT event_id AS u, {_NEXT} AS v, ts, lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next_ts FROM {{events}}) x WHERE v IS NOT NULL AND next_ts < ts + INTERVAL 1 DAY",
    "w7": f"SELECT u, v FROM {_OVERALL} x WHERE v IS NOT NULL",
    "w8": f"SELECT {scrambled('u')} AS u, {scrambled('v')} AS v FROM {_OVERALL} x WHERE v IS NOT NULL",
    "w9": f"SELECT doc_id * 2 AS u, d.id * 2 + 1 AS v FROM {_LINES} l JOIN {_dictionary(_LINES, 'h')} d ON l.h = d.s",
    "w10": "SELECT least(doc_id, m) AS u, greatest(doc_id, m) AS v FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY md5(text)) AS m FROM {documents}) x WHERE doc_id <> m",
    "w11": f"SELECT id AS u, next_id AS v FROM (SELECT {turn_id()} AS id, lead({turn_id()}) OVER (PARTITION BY conv_id ORDER BY turn) AS next_id FROM {{conversations}}) x WHERE next_id IS NOT NULL",
    "w12": f"SELECT page_id * 2 AS u, d.id * 2 + 1 AS v FROM {_HOSTS} p JOIN {_dictionary(_HOSTS, 'host')} d ON p.host = d.s",
    "w12b": f"SELECT DISTINCT page_id * 2 AS u, d.id * 2 + 1 AS v FROM {_HREFS} p JOIN {_dictionary(_HREFS, 'href')} d ON p.href = d.s",
    "w13": f"SELECT DISTINCT user_id * 2 AS u, d.id * 2 + 1 AS v FROM {{events}} e JOIN {_dictionary('{events}', 'event_type')} d ON e.event_type = d.s",
    "w13b": "SELECT DISTINCT user_id * 2 AS u, CAST({json_k} AS BIGINT) * 2 + 1 AS v FROM {events} WHERE {json_k} IS NOT NULL",
    # As SQL a nested loop; in Spark all pairs are compared block by block, see ``edges``.
    "w14": "SELECT a.vec_id AS u, b.vec_id AS v FROM {embeddings} a JOIN {embeddings} b ON a.vec_id < b.vec_id WHERE {cosine} >= 0.4",  # LEAST_COSINE
    "w15": "SELECT DISTINCT o_custkey * 2 AS u, l_partkey * 2 + 1 AS v FROM {orders} JOIN {lineitem} ON o_orderkey = l_orderkey",
}

_SPARK = {
    "unnest": "explode", "lines": "split(text, '\\\\n')", "json_k": "get_json_object(props, '$.k')",
    "cosine": "aggregate(zip_with(a.embedding, b.embedding, (x, y) -> CAST(x AS DOUBLE) * y), 0D, (s, x) -> s + x)"
    " / sqrt(aggregate(a.embedding, 0D, (s, x) -> s + CAST(x AS DOUBLE) * x) * aggregate(b.embedding, 0D, (s, x) -> s + CAST(x AS DOUBLE) * x))",
}
_DUCK = {
    "unnest": "unnest", "lines": "string_split(text, chr(10))", "json_k": "json_extract_string(props, '$.k')",
    "cosine": "list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[])",
}


def spark_sql(text: str, sf_dir: str) -> str:
    return text.format(**{t: f"parquet.`{sf_dir}/{t}.parquet`" for t in TABLES}, **_SPARK)


def duck_sql(text: str) -> str:
    return text.format(**{t: t for t in TABLES}, **_DUCK)


#: Workloads whose values begin alike, so that numbering them by their first characters would be one task's work.
NUMBERED = {"w12": (_HOSTS, "host"), "w12b": (_HREFS, "href")}


def edges(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The edge DataFrame ``(u, v)`` of a workload."""
    if name == "w14":
        return cosine_join(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), "vec_id", "embedding", LEAST_COSINE)
    if name not in NUMBERED:
        return spark.sql(spark_sql(EDGES[name], sf_dir))
    source, value = NUMBERED[name]
    found = spark.sql(spark_sql(f"SELECT * FROM {source} x", sf_dir))
    ends = found.join(dictionary(found, value), value).select((F.col("page_id") * 2).alias("u"), (F.col("id") * 2 + 1).alias("v"))
    return ends.distinct() if name == "w12b" else ends


def links(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Edges with the components of ``edges``, fewer where rows are copies of each other."""
    if name == "w14":
        return cosine_links(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), "vec_id", "embedding", LEAST_COSINE)
    return edges(spark, sf_dir, name)


def edges_from_sql(spark: SparkSession, query: str) -> DataFrame:
    """Edges from any SQL text that returns ``u`` and ``v``."""
    from graphcc.schema import check_edges

    return check_edges(spark.sql(query))


def replicate(e: DataFrame, times: int, stride: int, bridge: bool = False) -> DataFrame:
    """``times`` copies with ids shifted by ``stride``, disjoint if no id lies that far from another; ``bridge`` ties each copy's least node to the next copy's."""
    copies = e.select("u", "v", F.explode(F.sequence(F.lit(0), F.lit(times - 1))).alias("c")).select((F.col("u") + F.col("c") * stride).alias("u"), (F.col("v") + F.col("c") * stride).alias("v"))
    if not bridge:
        return copies
    first = e.agg(F.min(F.least("u", "v")).alias("m"))
    ties = first.select(F.explode(F.sequence(F.lit(1), F.lit(max(1, times - 1)))).alias("c"), "m").where(F.col("c") < times)
    return copies.unionByName(ties.select((F.col("m") + (F.col("c") - 1) * stride).alias("u"), (F.col("m") + F.col("c") * stride).alias("v")))


def copies_apart(e: DataFrame, times: int) -> DataFrame:
    """``times`` copies that share no id, whatever the ids: copy ``c`` of node ``x`` is ``x * times + c``."""
    name = lambda c: (F.col(c) * times + F.col("c")).alias(c)
    return e.select("u", "v", F.explode(F.sequence(F.lit(0), F.lit(times - 1))).alias("c")).select(name("u"), name("v"))


def shifted(id_: str, times: int, stride: int) -> Column:
    """The id that ``replicate`` gives a node of ``copies_apart``."""
    copy = F.pmod(F.col(id_), F.lit(times))
    return F.expr(f"(`{id_}` - pmod(`{id_}`, {times})) div {times}") + copy * stride
