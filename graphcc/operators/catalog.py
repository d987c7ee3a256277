"""Everyday operators around the methods, one query each, with their SQL for DuckDB."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphcc.functions.ids import dictionary
from graphcc.oracles import workload_sql
from graphcc.operators import graph_results as G
from graphcc.operators.joins import asof_join, range_join
from graphcc.plans.components import connected_components
from graphcc.schema import canonicalize
from graphcc.session import scratch_path
from graphcc.sources import synthetic
from graphcc.sources.workloads import EDGES, duck_sql, edges, edges_from_sql, spark_sql

#: Edges that one task of the Python source makes, at most about.
CHAIN_ROWS = 1 << 20
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def both(name: str, text: str) -> None:
    """A query whose SQL is the same text for Spark and DuckDB."""
    query(name, duck_sql(text))(lambda spark, d: spark.sql(spark_sql(text, d)))


def cc(spark: SparkSession, d: str, w: str, **options) -> DataFrame:
    return connected_components(edges(spark, d, w), **options)


# Sources and sinks.
both("op_parquet_pruned", "SELECT o_orderkey, o_custkey FROM {orders} WHERE o_totalprice > 100000")
_W1 = duck_sql(EDGES["w1"])


def _through(fmt: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        path = scratch_path(spark, fmt)
        e = edges(spark, d, "w1")
        if fmt == "text":
            e.select(F.concat_ws(" ", "u", "v")).write.text(path)
            parts = F.split("value", " ")
            return spark.read.text(path).select(parts[0].cast("long").alias("u"), parts[1].cast("long").alias("v"))
        e.write.format(fmt).save(path)
        return spark.read.schema("u long, v long").format(fmt).load(path)

    return run


for _f in ("csv", "json", "orc", "text"):
    query(f"op_source_{_f}", _W1)(_through(_f))
query("op_edges_from_sql", duck_sql(EDGES["w2"]))(lambda spark, d: edges_from_sql(spark, spark_sql(EDGES["w2"], d)))


@query("op_synthetic_source", "SELECT u, v FROM (SELECT o_orderkey AS u, lead(o_orderkey) OVER (ORDER BY o_orderkey) AS v FROM (SELECT DISTINCT o_orderkey FROM orders WHERE o_orderkey IS NOT NULL) k) x WHERE v IS NOT NULL")
def _(spark, d):
    """A chain of the Python source over the orders: its node i is the order with the i-th key."""
    synthetic.register(spark)
    keys = dictionary(t(spark, d, "orders"), "o_orderkey")
    n = keys.count()
    parts = max(1, min(n, spark.sparkContext.defaultParallelism), n // CHAIN_ROWS)
    chain = spark.read.format("synthetic_graph").option("shape", "chain").option("n", max(0, n - 1)).option("partitions", parts).load()
    u, v = (keys.select(F.col("id").alias(f"{end}_id"), F.col("o_orderkey").alias(end)) for end in "uv")
    return chain.toDF("u_id", "v_id").join(u, "u_id").join(v, "v_id").select("u", "v")


@query("op_bucketed_sink", f"SELECT component, count(*)::BIGINT AS nodes FROM ({workload_sql('w2b')}) GROUP BY component")
def _(spark, d):
    name = f"stars_{scratch_path(spark, 'b').rsplit('-', 1)[1]}"
    cc(spark, d, "w2b").write.option("path", scratch_path(spark, "bucketed")).bucketBy(8, "component").sortBy("component").saveAsTable(name)
    return spark.table(name).groupBy("component").agg(F.count(F.lit(1)).alias("nodes"))


@query("op_partitioned_sink", f"SELECT node, component FROM ({workload_sql('w2b')}) WHERE component % 4 = 2")
def _(spark, d):
    path = scratch_path(spark, "partitioned")
    cc(spark, d, "w2b").withColumn("part", F.col("component") % 4).write.partitionBy("part").parquet(path)
    return spark.read.parquet(path).where("part = 2").select("node", "component")


@query("op_export_modes", f"SELECT node, component, 2::BIGINT AS copies FROM ({workload_sql('w2')})")
def _(spark, d):
    path, stars = scratch_path(spark, "export"), cc(spark, d, "w2")
    for mode in ("overwrite", "overwrite", "append"):
        stars.write.mode(mode).json(path)
    return spark.read.schema("node long, component long").json(path).groupBy("node", "component").agg(F.count(F.lit(1)).alias("copies"))


# Projections and filters.
both("op_edge_builder", "SELECT least(u, v) AS u, greatest(u, v) AS v FROM (" + EDGES["w4"] + ") e WHERE u IS NOT NULL AND v IS NOT NULL AND u <> v")
both("op_predicates", "SELECT page_id, url FROM {pages} WHERE (url LIKE 'https://%' OR url LIKE '%#top') AND page_id BETWEEN 10 AND 2000 AND NOT (page_id IN (11, 12, 13)) AND html IS NOT NULL")
query("op_rlike", "SELECT page_id FROM pages WHERE regexp_matches(url, '^https?://(www|m)[.]')")(lambda spark, d: t(spark, d, "pages").where(F.col("url").rlike("^https?://(www|m)[.]")).select("page_id"))
query("op_canonicalize", f"SELECT DISTINCT least(u, v) AS u, greatest(u, v) AS v FROM ({duck_sql(EDGES['w3'])}) e WHERE u <> v")(lambda spark, d: canonicalize(edges(spark, d, "w3")))

# Joins.
_J = "SELECT o_orderstatus, count(*)::BIGINT AS n, sum(l_quantity)::DOUBLE AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus"
for _h in ("shuffle_hash", "merge"):

    @query(f"op_join_{_h}", _J)
    def _(spark, d, hint=_h):
        o, li = t(spark, d, "orders").select("o_orderkey", "o_orderstatus"), t(spark, d, "lineitem").select("l_orderkey", "l_quantity")
        return o.hint(hint).join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").cast("double").alias("quantity"))


@query("op_broadcast_join", "SELECT r_name, count(*)::BIGINT AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def _(spark, d):
    nations = t(spark, d, "nation").join(t(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")  # 25 rows by definition
    return t(spark, d, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("customers"))


both("op_left_outer_self_join", "WITH p AS (SELECT greatest(u, v) AS child, min(least(u, v)) AS parent FROM (" + EDGES["w2"] + ") e GROUP BY 1) SELECT a.child, coalesce(b.parent, a.parent) AS parent FROM p a LEFT JOIN p b ON a.parent = b.child")
query("op_semi_join", f"WITH s AS ({workload_sql('w2b')}), e AS ({duck_sql(EDGES['w2b'])}) SELECT u, v FROM e WHERE u IN (SELECT node FROM s WHERE component = (SELECT min(component) FROM s))")(
    lambda spark, d: (lambda e, s: G.induced(e, s, s.agg(F.min("component")).first()[0]))(edges(spark, d, "w2b"), cc(spark, d, "w2b"))
)
both("op_anti_join", "SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)")


@query("op_full_outer_join", "SELECT 0::BIGINT AS only_one, 0::BIGINT AS only_other, 0::BIGINT AS different")
def _(spark, d):
    a, b = cc(spark, d, "w2b").withColumnRenamed("component", "x"), cc(spark, d, "w2b", method="star_contraction").withColumnRenamed("component", "y")
    count = lambda c: F.coalesce(F.sum(c.cast("long")), F.lit(0))
    return a.join(b, "node", "full_outer").agg(count(F.col("y").isNull()).alias("only_one"), count(F.col("x").isNull()).alias("only_other"), count(F.col("x") != F.col("y")).alias("different"))


both("op_theta_join", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM {supplier} a JOIN {supplier} b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) < 5")
query("op_similarity_join", duck_sql(EDGES["w14"]))(lambda spark, d: edges(spark, d, "w14"))
both("op_self_join", EDGES["w5"])


@query("op_range_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.event_id < b.event_id AND a.user_id <> b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 10000000")
def _(spark, d):
    e = t(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    l, r = (e.select(*[F.col(c).alias(f"{c}_{s}") for c in e.columns]) for s in "lr")  # noqa: E741
    near = range_join(l, r, "us_l", "us_r", 10_000_000, (F.col("event_id_l") < F.col("event_id_r")) & (F.col("user_id_l") != F.col("user_id_r")))
    return near.select(F.col("event_id_l").alias("a"), F.col("event_id_r").alias("b"))


@query("op_asof_join", "SELECT event_id, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_mark FROM events")
def _(spark, d):
    e = t(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    marks = e.where("event_type = 'click'").withColumn("mark", F.col("event_id"))
    return asof_join(e, marks.select("user_id", "ts", "event_id", "mark"), ["user_id"], ["ts", "event_id"], "mark").select("event_id", "last_mark")


# Aggregates.
both("op_hash_aggregate", "SELECT l_returnflag, l_linestatus, count(*) AS n, min(l_shipdate) AS first_day, max(l_shipdate) AS last_day, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS DOUBLE) AS price, min_by(l_orderkey, l_orderkey) AS least_order FROM {lineitem} GROUP BY l_returnflag, l_linestatus")


@query("op_distinct_and_percentiles", f"SELECT count(*)::BIGINT AS components, quantile_cont(nodes, 0.5)::DOUBLE AS median, quantile_cont(nodes, 0.9)::DOUBLE AS p90, true AS approx_close FROM (SELECT component, count(*) AS nodes FROM ({workload_sql('w2b')}) GROUP BY component)")
def _(spark, d):
    sizes = G.component_sizes(cc(spark, d, "w2b"))
    close = F.abs(F.approx_count_distinct("component", 0.02) / F.count(F.lit(1)) - 1) < 0.1
    return sizes.agg(F.countDistinct("component").alias("components"), F.percentile("nodes", 0.5).alias("median"), F.percentile("nodes", 0.9).alias("p90"), close.alias("approx_close"))


query("op_collect_members", f"SELECT component, string_agg(node::VARCHAR, ',' ORDER BY node) AS members FROM ({workload_sql('w2')}) GROUP BY component HAVING count(*) <= 4")(
    lambda spark, d: (lambda s: s.join(G.component_sizes(s).where("nodes <= 4").select("component"), "component", "left_semi"))(cc(spark, d, "w2")).groupBy("component").agg(F.array_join(F.sort_array(F.collect_list("node")), ",").alias("members"))
)
_C = "FROM {customer} JOIN {nation} ON c_nationkey = n_nationkey"
both("op_cube", "SELECT n_regionkey, c_mktsegment, count(*) AS n " + _C + " GROUP BY CUBE (n_regionkey, c_mktsegment)")
both("op_rollup", "SELECT n_regionkey, c_nationkey, count(*) AS n " + _C + " GROUP BY ROLLUP (n_regionkey, c_nationkey)")
both("op_grouping_sets", "SELECT n_regionkey, c_mktsegment, count(*) AS n " + _C + " GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment), ())")
_TYPES = ["click", "purchase", "signup", "view"]
query("op_pivot", "SELECT user_id % 10 AS band, " + ", ".join(f"count(*) FILTER (event_type = '{x}')::BIGINT AS {x}" for x in _TYPES) + " FROM events GROUP BY 1")(
    lambda spark, d: t(spark, d, "events").groupBy((F.col("user_id") % 10).alias("band")).pivot("event_type", _TYPES).agg(F.count(F.lit(1))).na.fill(0)
)

# Windows, sorting, sets.
both("op_window_ranks", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS quarter, percent_rank() OVER w AS share FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
both("op_gaps_and_islands", "SELECT user_id, island, count(*) AS events, min(event_id) AS first_event FROM (SELECT *, sum(CASE WHEN before IS NULL OR ts >= before + INTERVAL 1 DAY THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS island FROM (SELECT user_id, event_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM {events}) x) y GROUP BY user_id, island")
query("op_running_share", f"SELECT component, nodes, sum(nodes) OVER (PARTITION BY nodes % 8 ORDER BY nodes DESC, component)::BIGINT AS running FROM (SELECT component, count(*)::BIGINT AS nodes FROM ({workload_sql('w2b')}) GROUP BY component)")(
    lambda spark, d: G.component_sizes(cc(spark, d, "w2b")).withColumn("running", F.sum("nodes").over(Window.partitionBy(F.col("nodes") % 8).orderBy(F.desc("nodes"), "component")))
)
query("op_top_k", f"SELECT component, count(*)::BIGINT AS nodes FROM ({workload_sql('w2b')}) GROUP BY component ORDER BY nodes DESC, component LIMIT 10")(lambda spark, d: G.component_sizes(cc(spark, d, "w2b")).orderBy(F.desc("nodes"), "component").limit(10))
both("op_top_k_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM {orders}) x WHERE r <= 2")
for _n, _op in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT"), ("union_all", "UNION ALL"), ("except_all", "EXCEPT ALL"), ("intersect_all", "INTERSECT ALL")):
    both(f"op_{_n}", "SELECT o_custkey AS k FROM {orders} WHERE o_totalprice > 200000 " + _op + " SELECT o_custkey FROM {orders} WHERE o_orderstatus = 'F'")

# Scalars.
both("op_strings", "SELECT page_id, upper(trim(url)) AS u, length(url) AS n, substring(url, 1, 12) AS head, md5(url) AS h, concat(lower(url), '!') AS c, regexp_extract(url, '://([^/?#]+)', 1) AS host, replace(url, 'http', 'x') AS r FROM {pages}")
both("op_dates", "SELECT date_trunc('month', o_orderdate) AS month, count(*) AS n, CAST(sum(year(o_orderdate)) AS BIGINT) AS years FROM {orders} WHERE o_orderdate < DATE '1996-01-01' + INTERVAL 90 DAY GROUP BY 1")
both("op_math", "SELECT o_orderkey, floor(sqrt(o_orderkey)) AS s, abs(5 - o_orderkey) AS a, o_orderkey % 7 AS m, round(pow(o_orderkey % 10, 2), 3) AS p, floor(log2(o_orderkey + 1)) AS band FROM {orders}")
query("op_arrays", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS positive, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x)), 4) AS norm FROM embeddings")(
    lambda spark, d: t(spark, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.round(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x), 4).alias("norm"))
)
query("op_maps_and_structs", "SELECT user_id, count(*) FILTER (event_type = 'click')::BIGINT AS clicks FROM events GROUP BY user_id HAVING count(*) FILTER (event_type = 'click') > 0")(
    lambda spark, d: t(spark, d, "events").groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m")).select("user_id", F.try_element_at("m", F.lit("click")).alias("clicks")).where("clicks IS NOT NULL")
)
query("op_json", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")(lambda spark, d: t(spark, d, "events").select("event_id", F.from_json("props", "k long").getField("k").alias("k")))
query("op_hashes", "SELECT page_id, md5(url) AS m, sha256(url) AS s, ('0x' || substr(md5(url), 1, 8))::BIGINT AS c FROM pages")(
    lambda spark, d: t(spark, d, "pages").select("page_id", F.md5("url").alias("m"), F.sha2("url", 256).alias("s"), F.conv(F.substring(F.md5("url"), 1, 8), 16, 10).cast("long").alias("c"))
)
query("op_dictionary_ids", "SELECT l AS line, row_number() OVER (ORDER BY l) - 1 AS id FROM (SELECT DISTINCT l_shipdate::DATE::VARCHAR AS l FROM lineitem)")(
    lambda spark, d: dictionary(t(spark, d, "lineitem").select(F.col("l_shipdate").cast("date").cast("string").alias("line")), "line")
)

# Graph results.
for _w in ("w2b", "w3", "w9"):
    _s = workload_sql(_w)
    query(f"lcc_report_{_w}", f"SELECT count(*)::BIGINT AS components, max(nodes)::BIGINT AS largest, sum((nodes > 5000)::INT)::BIGINT AS large, sum(nodes)::BIGINT AS nodes FROM (SELECT component, count(*) AS nodes FROM ({_s}) GROUP BY 1)")(lambda spark, d, w=_w: G.lcc_report(cc(spark, d, w)))
    query(f"size_histogram_{_w}", f"SELECT floor(log2(nodes))::BIGINT AS band, count(*)::BIGINT AS components, sum(nodes)::BIGINT AS nodes FROM (SELECT component, count(*) AS nodes FROM ({_s}) GROUP BY 1) GROUP BY 1")(lambda spark, d, w=_w: G.size_histogram(cc(spark, d, w)))
    _d = f"SELECT u AS node, count(DISTINCT v)::BIGINT AS degree FROM (SELECT u, v FROM ({duck_sql(EDGES[_w])}) e UNION SELECT v, u FROM ({duck_sql(EDGES[_w])}) e) x WHERE u <> v GROUP BY u"
    query(f"degree_profile_{_w}", _d)(lambda spark, d, w=_w: G.degree(edges(spark, d, w)))
    query(
        f"graph_class_{_w}",
        f"WITH g AS ({_d}), s AS (SELECT component, count(*) AS n FROM ({_s}) GROUP BY 1), x AS (SELECT (SELECT count(*) FROM g)::BIGINT AS nodes, (SELECT sum(degree) // 2 FROM g)::BIGINT AS edges, (SELECT max(degree) FROM g)::BIGINT AS max_degree, (SELECT count(*) FROM s)::BIGINT AS components, (SELECT max(n) FROM s)::BIGINT AS largest, (SELECT sum((n > 5000)::INT) FROM s)::BIGINT AS large) SELECT *, CASE WHEN largest > 5000 THEN 'd' WHEN edges > 4 * nodes THEN 'b' WHEN max_degree <= 2 THEN 'c' ELSE 'a' END AS class FROM x",
    )(lambda spark, d, w=_w: (lambda e: G.graph_profile(e, connected_components(e)))(edges(spark, d, w)))
query("component_sizes_w9", f"SELECT component, count(*)::BIGINT AS nodes FROM ({workload_sql('w9')}) GROUP BY 1")(lambda spark, d: G.component_sizes(cc(spark, d, "w9")))
query("members_w2b", f"WITH s AS ({workload_sql('w2b')}) SELECT node FROM s WHERE component = (SELECT min(component) FROM s)")(lambda spark, d: (lambda s: G.members(s, s.agg(F.min("component")).first()[0]))(cc(spark, d, "w2b")))
query("same_component_w2", f"WITH s AS ({workload_sql('w2')}), e AS (SELECT DISTINCT u AS a, v + 2 AS b FROM ({duck_sql(EDGES['w2'])}) x) SELECT a, b, coalesce(s1.component = s2.component, false) AS same FROM e LEFT JOIN s s1 ON s1.node = a LEFT JOIN s s2 ON s2.node = b")(
    lambda spark, d: G.same_component(cc(spark, d, "w2"), edges(spark, d, "w2").select(F.col("u").alias("a"), (F.col("v") + 2).alias("b")).distinct())
)
query("contract_w2b_by_w2", f"WITH l AS ({workload_sql('w2')}), e AS ({duck_sql(EDGES['w2b'])}), x AS (SELECT coalesce(a.component, u) AS x, coalesce(b.component, v) AS y FROM e LEFT JOIN l a ON a.node = u LEFT JOIN l b ON b.node = v) SELECT DISTINCT least(x, y) AS u, greatest(x, y) AS v FROM x WHERE x <> y")(
    lambda spark, d: G.contract(edges(spark, d, "w2b"), cc(spark, d, "w2"))
)
_SPLIT = f"WITH RECURSIVE all_e AS (SELECT DISTINCT u, v FROM ({duck_sql(EDGES['w9'])}) z), deg AS (SELECT n, count(*) AS c FROM (SELECT u AS n FROM all_e UNION ALL SELECT v FROM all_e) q GROUP BY n), e AS (SELECT u, v FROM all_e WHERE u NOT IN (SELECT n FROM deg WHERE c > 20) AND v NOT IN (SELECT n FROM deg WHERE c > 20)),"
query("split_lcc_w9", _SPLIT + " s AS (SELECT u, v FROM e UNION SELECT v, u FROM e), cc(node, component) USING KEY (node) AS (SELECT u, min(least(u, v)) FROM s GROUP BY u UNION SELECT s.v, min(cc.component) FROM cc JOIN s ON s.u = cc.node JOIN recurring.cc r ON r.node = s.v WHERE cc.component < r.component GROUP BY s.v) SELECT node, component FROM cc")(lambda spark, d: G.split_lcc(edges(spark, d, "w9"), 20))


@query("op_enrich_components", f"SELECT component, count(*)::BIGINT AS customers, sum(c_acctbal::DECIMAL(18, 2))::DOUBLE AS balance FROM ({workload_sql('w1')}) s JOIN customer ON s.node = c_custkey * 2 GROUP BY component")
def _(spark, d):
    c = t(spark, d, "customer").select((F.col("c_custkey") * 2).alias("node"), F.col("c_acctbal").cast("decimal(18,2)").alias("b"))
    return cc(spark, d, "w1").join(c, "node").groupBy("component").agg(F.count(F.lit(1)).alias("customers"), F.sum("b").cast("double").alias("balance"))


# Functions in Python.
_COS = duck_sql("SELECT a.vec_id AS a, b.vec_id AS b, round({cosine}, 6) AS cosine FROM {embeddings} a JOIN {embeddings} b ON a.label = b.label AND a.vec_id < b.vec_id")


def _cosine_vectorised(e):
    """Cosines of all pairs of rows of ``e`` that share a label, by a vectorised function."""
    import numpy as np

    @F.pandas_udf("double")
    def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
        if not len(a):
            return pd.Series([], dtype=float)
        x, y = (np.stack(s.to_numpy()).astype(float) for s in (a, b))
        return pd.Series((x * y).sum(1) / np.sqrt((x * x).sum(1) * (y * y).sum(1)))

    pairs = e.alias("a").join(e.alias("b"), F.expr("a.label = b.label AND a.vec_id < b.vec_id"))
    return pairs.select(F.col("a.vec_id").alias("a"), F.col("b.vec_id").alias("b"), F.round(cosine("a.embedding", "b.embedding"), 6).alias("cosine"))


query("udf_cosine_vectorised", _COS)(lambda spark, d: _cosine_vectorised(t(spark, d, "embeddings")))
query("udf_cosine_builtin", _COS)(lambda spark, d: spark.sql(spark_sql("SELECT a.vec_id AS a, b.vec_id AS b, round({cosine}, 6) AS cosine FROM {embeddings} a JOIN {embeddings} b ON a.label = b.label AND a.vec_id < b.vec_id", d)))


@query("udf_component_checksum", f"SELECT component, bit_xor(node)::BIGINT AS checksum FROM ({workload_sql('w2b')}) GROUP BY component")
def _(spark, d):
    @F.pandas_udf("long")
    def xor(x: pd.Series) -> int:
        out = 0
        for v in x:
            out ^= int(v)
        return out

    return cc(spark, d, "w2b").groupBy("component").agg(xor("node").alias("checksum"))


@query("udtf_edge_lists", duck_sql(EDGES["w1"]))
def _(spark, d):
    @F.udtf(returnType="u: bigint, v: bigint")
    class Edges:
        def eval(self, text: str):
            for pair in (text or "").split():
                a, _, b = pair.partition("-")
                yield int(a), int(b)

    e = edges(spark, d, "w1").groupBy("u").agg(F.concat_ws(" ", F.collect_list(F.concat_ws("-", "u", "v"))).alias("text"))
    e.createOrReplaceTempView("edge_lists")
    spark.udtf.register("edges_of", Edges)
    return spark.sql("SELECT t.u, t.v FROM edge_lists, LATERAL edges_of(text) t")


@query("udf_finish_component", workload_sql("w6b"))
def _(spark, d):
    """Bounded groups (one user's chain) finished one by one."""

    def finish(pdf: pd.DataFrame) -> pd.DataFrame:
        from graphcc.plans.local_forest import local_roots

        ids, root = local_roots(pdf["u"].to_numpy(), pdf["v"].to_numpy())
        return pd.DataFrame({"node": ids, "component": root})

    users = t(spark, d, "events").select(F.col("event_id").alias("u"), "user_id")
    return edges(spark, d, "w6b").join(users, "u").groupBy("user_id").applyInPandas(finish, "node long, component long")


@query("udf_cogroup_compare", "SELECT 0::BIGINT AS different")
def _(spark, d):
    def compare(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"n": [len(set(map(tuple, a[["node", "component"]].to_numpy())) ^ set(map(tuple, b[["node", "component"]].to_numpy())))]})

    a, b = (x.withColumn("g", F.col("node") % 64) for x in (cc(spark, d, "w2b"), cc(spark, d, "w2b", method="lfpe_no_local")))
    return a.groupBy("g").cogroup(b.groupBy("g")).applyInPandas(compare, "n long").agg(F.sum("n").alias("different"))


@query("udf_arrow_kernel", f"SELECT DISTINCT unnest([u, v]) AS node FROM ({duck_sql(EDGES['w6'])}) e")
def _(spark, d):
    def ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.concat_arrays([b.column(0), b.column(1)]).unique()], ["node"])

    return edges(spark, d, "w6").mapInArrow(ends, "node long").distinct()


@query("sql_components_view", f"SELECT o_orderstatus, count(DISTINCT component)::BIGINT AS components FROM ({workload_sql('w1')}) s JOIN orders ON s.node = o_orderkey * 2 + 1 GROUP BY o_orderstatus")
def _(spark, d):
    cc(spark, d, "w1").createOrReplaceTempView("components")
    t(spark, d, "orders").createOrReplaceTempView("orders_in")
    return spark.sql("SELECT o_orderstatus, count(DISTINCT component) AS components FROM components JOIN orders_in ON node = o_orderkey * 2 + 1 GROUP BY o_orderstatus")


# The quotient of all order-part links, beside that of a part of them.
query(
    "contract_w3_by_w2",
    f"WITH l AS ({workload_sql('w2')}), e AS ({duck_sql(EDGES['w3'])}), x AS (SELECT coalesce(a.component, u) AS x, coalesce(b.component, v) AS y FROM e LEFT JOIN l a ON a.node = u LEFT JOIN l b ON b.node = v) SELECT DISTINCT least(x, y) AS u, greatest(x, y) AS v FROM x WHERE x <> y",
)(lambda spark, d: G.contract(edges(spark, d, "w3"), cc(spark, d, "w2")))


@query("op_order_by", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey")
def _(spark, d):
    return t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey")


@query("op_sort_within_partitions", "SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey)::BIGINT AS at FROM orders")
def _(spark, d):
    """Orders of a customer numbered by one pass over partitions that hold whole customers, sorted."""

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, at = None, 0
        for b in batches:
            places = []
            for customer in b.column(0).to_pylist():
                at = at + 1 if customer == last else 1
                last = customer
                places.append(at)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(places, pa.int64())], ["o_custkey", "o_orderkey", "at"])

    dealt = t(spark, d, "orders").select("o_custkey", "o_orderkey").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")
    return dealt.mapInArrow(number, "o_custkey long, o_orderkey long, at long")


query("op_to_json", "SELECT event_id, '{\"u\":' || user_id || ',\"t\":\"' || event_type || '\"}' AS j FROM events WHERE user_id IS NOT NULL AND event_type IS NOT NULL")(
    lambda spark, d: t(spark, d, "events").where("user_id IS NOT NULL AND event_type IS NOT NULL").select("event_id", F.to_json(F.struct(F.col("user_id").alias("u"), F.col("event_type").alias("t"))).alias("j"))
)


@query("op_row_hashes", "SELECT page_id, true AS same, true AS bounded FROM pages")
def _(spark, d):
    """The 64-bit, 32-bit and checksum hashes of equal values agree, whatever the expression that gave them."""
    again = F.concat(F.substring("url", 1, 4), F.substring("url", 5, 1 << 20))
    same = (F.xxhash64("url") == F.xxhash64(again)) & (F.hash("url") == F.hash(again)) & (F.crc32(F.encode("url", "UTF-8")) == F.crc32(F.encode(again, "UTF-8")))
    return t(spark, d, "pages").select("page_id", same.alias("same"), F.crc32(F.encode("url", "UTF-8")).between(0, 2**32 - 1).alias("bounded"))


_W6_FAR = f"SELECT component, (count(*) - 1)::BIGINT AS least_diameter FROM ({workload_sql('w6')}) GROUP BY component"


@query("diameter_hint_w6", _W6_FAR)
def _(spark, d):
    """How far the farthest node lies from the smallest of its component: a lower bound of the diameter, all of it in a chain."""
    return G.diameter_hint(edges(spark, d, "w6"), cc(spark, d, "w6"))
