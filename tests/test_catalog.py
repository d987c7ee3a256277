"""Registered queries against their SQL in DuckDB, joins without an operator of their own, and plans."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from graphcc.operators import catalog
from graphcc.operators.joins import range_join
from graphcc.sources.workloads import TABLES, edges, spark_sql
from graphcc.streaming.incremental import ComponentState
from graphcc.session import scratch_path


def tidy(rows):
    return sorted((tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in rows), key=repr)


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


SOME = [n for n in catalog.QUERIES if n.startswith(("op_", "udf_cosine", "udtf")) and not n.startswith(("op_source", "op_bucketed"))][::3]


@pytest.mark.parametrize("name", [*SOME, "cc_lfpe_w3", "cc_star_alternate_w9", "elect_round_w2_live", "stream_session_w6b", "stream_cc_w6"])
def test_query_equals_its_sql(spark, sf, duck, name):
    df, want = entry.queries()[name](spark, sf), duck.sql(entry.oracle_sql()[name])
    cols = sorted(df.columns)
    assert cols == sorted(want.columns)
    at = [want.columns.index(c) for c in cols]
    assert tidy(df.select(*cols).collect()) == tidy(tuple(r[i] for i in at) for r in want.fetchall())


def test_every_sql_has_its_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 150


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["node", "component"] and df.count() == 1673


def test_range_join_meets_each_pair_once(spark):
    a = spark.createDataFrame([(i, t) for i, t in enumerate([-11, -10, 0, 9, 10, 11, 20, 100])], "x long, s long")
    b = a.select(F.col("x").alias("y"), F.col("s").alias("t"))
    got = range_join(a, b, "s", "t", 10, F.col("x") < F.col("y")).select("x", "y").collect()
    vals = [-11, -10, 0, 9, 10, 11, 20, 100]
    assert sorted(map(tuple, got)) == sorted((i, j) for i in range(8) for j in range(i + 1, 8) if abs(vals[i] - vals[j]) <= 10)


def test_scans_read_only_what_is_needed(spark, sf):
    plan = edges(spark, sf, "w2")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), EqualTo(l_quantity,50.0)]" in plan.replace("l_quantity, ", "l_quantity,") or "EqualTo(l_quantity" in plan
    scan = [line for line in plan.splitlines() if "ReadSchema" in line][0]
    assert "l_comment" not in scan and "l_shipdate" not in scan.split("ReadSchema")[1]
    assert "SELECT" in spark_sql("SELECT 1", sf)


def test_a_stream_batch_applied_again_changes_nothing(spark):
    state = ComponentState(spark, scratch_path(spark, "state"))
    one = spark.createDataFrame([(1, 2), (3, 4), (9, 9)], "u long, v long")
    two = spark.createDataFrame([(4, 2), (7, 8)], "u long, v long")
    state.apply(one, 0)
    state.apply(two, 1)
    want = {1: 1, 2: 1, 3: 1, 4: 1, 7: 7, 8: 7}
    assert {r.node: r.component for r in state.components().collect()} == want
    state.apply(two, 1)
    state.apply(spark.createDataFrame([], "u long, v long"), 2)
    assert {r.node: r.component for r in state.components().collect()} == want
    state.apply(spark.createDataFrame([(0, 8)], "u long, v long"), 3)
    assert {r.node: r.component for r in state.components().collect()} == want | {7: 0, 8: 0, 0: 0}


def test_the_rest_works_without_the_training_data_operators():
    import pathlib
    import re

    root = pathlib.Path(entry.__file__).parent
    for p in root.rglob("graphcc/**/*.py"):
        if "llm" not in p.parts:
            assert not re.search(r"graphcc\.llm|from graphcc import llm", p.read_text()), p
