"""Jobs beyond the sizes of the given tables: what once met a limit."""

import random

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from graphcc.operators import joins
from graphcc.operators.joins import cosine_join, cosine_links
from graphcc.plans.components import connected_components
from graphcc.sources.workloads import copies_apart, shifted


def test_sequential_takes_any_number_of_edges(spark):
    e = spark.range(2_100_000).select((F.col("id") % 1000 * 3 - 5).alias("u"), (F.col("id") % 701 * 3 + 10_000).alias("v"))
    e = e.unionByName(spark.createDataFrame([(7, 7), (2**62, -(2**63)), (2**62, 5)], "u long, v long"))
    for options in ({}, {"weighted": False}, {"compress": False}):
        got = connected_components(e, method="sequential", **options)
        assert {tuple(r) for r in got.groupBy("component").agg(F.count("node")).collect()} == {(-(2**63), 3), (-5, 1000 + 701)}, options


VECTORS = "vec_id long, embedding array<float>, label int"


def rows_of(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.mark.parametrize("block", [8192, 7])
def test_similar_pairs_of_awkward_vectors(spark, tmp_path, monkeypatch, block):
    monkeypatch.setattr(joins, "BLOCK_ROWS", block)
    r = random.Random(3)
    rows = [(i, [r.gauss(0, 1) for _ in range(4)], 0) for i in range(40)]
    rows += [(100 + i, rows[5][1], 0) for i in range(9)] + [(7, rows[6][1], 0), (200, [0.0] * 4, 0), (201, [float("inf"), 0.0, 0.0, 0.0], 0), (202, [1e-40] * 4, 0), (203, [2.0, 0.0, 0.0, 0.0], 0)]
    rows += [(204, [0.4 * 5, 84**0.5 / 2, 0.0, 0.0], 0), (205, [2.0, 21**0.5, 0.0, 0.0], 0), (206, None, 0)]
    spark.createDataFrame(rows, VECTORS).write.parquet(f"{tmp_path}/embeddings.parquet")
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{tmp_path}/embeddings.parquet/*.parquet')")
    for name in ("op_similarity_join", "cc_lfpe_w14"):
        got = entry.queries()[name](spark, str(tmp_path))
        assert rows_of(got) == sorted(duck.sql(f"SELECT {', '.join(got.columns)} FROM ({entry.oracle_sql()[name]})").fetchall()), name
    plan = entry.queries()["op_similarity_join"](spark, str(tmp_path))._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_vectors_in_no_pair_and_links_of_copies(spark):
    some = [(1, [1.0, 0.0], 0), (2, [1.0, None], 0), (3, [1.0], 0), (4, [], 0), (None, [1.0, 0.0], 0), (5, [2.0, 0.0], 0), (6, [-1.0, 0.0], 0)]
    df = spark.createDataFrame(some, VECTORS)
    assert rows_of(cosine_join(df, "vec_id", "embedding", 0.4)) == [(1, 5)]
    copies = spark.createDataFrame([(i, [1.0, float(i % 2)], 0) for i in range(300)], VECTORS)
    assert cosine_links(copies, "vec_id", "embedding", 0.4).count() == 299  # of 44850 pairs
    assert cosine_join(copies, "vec_id", "embedding", 0.4).count() == 300 * 299 // 2


def test_recursive_sql_makes_as_many_rows_as_it_needs(spark):
    name = "spark.sql.cteRecursionRowLimit"
    pairs = [(i, i + 1) for i in range(30)] + [(50 - i, 51 - i) for i in range(10)] + [(60, 62), (61, 62), (61, 63), (63, 60), (7, 7)]
    spark.conf.set(name, "100")
    try:
        stars = connected_components(spark.createDataFrame(pairs, "u long, v long"), method="recursive_sql", max_depth=3)
        assert spark.conf.get(name) == "100"
    finally:
        spark.conf.unset(name)
    assert dict(rows_of(stars)) == {i: 0 for i in range(31)} | {i: 41 for i in range(41, 52)} | {i: 60 for i in range(60, 64)}


def test_replicated_copies_stay_apart_beyond_the_stride(spark, tmp_path):
    rows = [(k, p, 50.0) for k, p in [(1, 1), (1, 2), (5_000_001, 3), (10_000_001, 2), (10_000_001, 5_000_001), (7, 9)]]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW lineitem AS SELECT * FROM read_parquet('{tmp_path}/lineitem.parquet/*.parquet')")
    for name in ("cc_lfpe_replicated", "cc_lfpe_replicated_bridge"):
        got = entry.queries()[name](spark, str(tmp_path))
        assert rows_of(got) == sorted(duck.sql(f"SELECT {', '.join(got.columns)} FROM ({entry.oracle_sql()[name]})").fetchall()), name
    negative = spark.createDataFrame([(-7, -6), (-6, 5)], "u long, v long")
    stars = connected_components(copies_apart(negative, 3))
    assert rows_of(stars.select(shifted("node", 3, 100), shifted("component", 3, 100))) == sorted((x + 100 * c, -7 + 100 * c) for x in (-7, -6, 5) for c in range(3))


def test_one_local_forest_of_more_nodes_than_the_bound(spark, tmp_path):
    n = 1_050_000
    chain = spark.range(n).select(F.explode(F.array(F.col("id"), F.col("id") + 1)).alias("l_orderkey"), F.col("id").alias("l_partkey"), F.lit(50.0).alias("l_quantity"))
    chain.write.parquet(f"{tmp_path}/lineitem.parquet")
    assert rows_of(entry.queries()["tree_shape_w2b_k1"](spark, str(tmp_path))) == [(2 * n, 1, 2 * n)]


def test_synthetic_chain_over_the_orders(spark, tmp_path):
    for name, keys in (("some", [5, None, -3, 5, 2**62, 9]), ("one", [4]), ("none", [])):
        at = f"{tmp_path}/{name}"
        spark.createDataFrame([(k,) for k in keys], "o_orderkey long").write.parquet(f"{at}/orders.parquet")
        got = entry.queries()["op_synthetic_source"](spark, at)
        held = sorted({k for k in keys if k is not None})
        assert got.columns == ["u", "v"] and rows_of(got) == list(zip(held, held[1:])), name
