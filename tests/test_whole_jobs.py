"""Queries that take the whole of their input, against SQL over all of it."""

import collections

import duckdb
from pyspark.sql import functions as F

import __spark_entry__ as entry
from graphcc.plans.components import connected_components
from graphcc.sources.workloads import edges
from tests.test_catalog import tidy


def same_as_sql(spark, sf, name):
    duck = duckdb.connect()
    for t in ("embeddings", "lineitem"):
        duck.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df, want = entry.queries()[name](spark, sf), duck.sql(entry.oracle_sql()[name])
    got = tidy(df.select(*want.columns).collect())
    assert got == tidy(want.fetchall())
    return got


def test_cosines_of_all_labels(spark, sf):
    for name in ("udf_cosine_vectorised", "udf_cosine_builtin"):
        assert len(same_as_sql(spark, sf, name)) == 12432  # W5 in FIXTURES.md


def test_quotient_of_all_order_part_links(spark, sf):
    whole = same_as_sql(spark, sf, "contract_w3_by_w2")
    part = entry.queries()["contract_w2b_by_w2"](spark, sf).collect()
    assert {tuple(r) for r in part} < {tuple(r) for r in whole}


def test_recursive_sql_walks_to_the_end(spark):
    chain = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 102), (102, 100)]
    stars = connected_components(spark.createDataFrame(chain, "u long, v long"), method="recursive_sql")
    assert {r.node: r.component for r in stars.collect()} == {i: 0 for i in range(41)} | {i: 100 for i in (100, 101, 102)}


def test_local_measures_of_eight_tasks(spark, sf):
    task = F.pmod(F.hash("u"), F.lit(8))  # where a repartition by u puts a row
    parts = collections.defaultdict(list)
    for r in edges(spark, sf, "w2").select("u", "v", task.alias("task")).collect():
        parts[r.task].append((r.u, r.v))
    roles, pairs, loops = collections.defaultdict(lambda: [0, 0]), 0, 0
    for part in parts.values():
        root = {x: x for e in part for x in e}
        while any(root[u] != root[v] for u, v in part):
            for u, v in part:
                root[u] = root[v] = min(root[u], root[v])
        for x, r in root.items():
            roles[x][x != r] += 1
            pairs, loops = pairs + (x != r), loops + (x == r)
    got = entry.queries()["local_reduction_w2_k8"](spark, sf).first()
    assert (got.pairs, got.self_links) == (pairs, loops)
    cases = {(r.as_parent, r.as_child): r.nodes for r in entry.queries()["proof_scenarios_w2_k8"](spark, sf).collect()}
    assert cases == collections.Counter(map(tuple, roles.values()))
    assert len(parts) > 1 and max(a + b for a, b in cases) > 1


def test_size_sweep_has_copies_apart_and_tied(spark, sf):
    from graphcc import experiments

    got = list(experiments.sizes(spark, sf, copies=(2,), workloads=("w2b",)))
    assert len(got) == 2 * len(experiments.METHODS) and all(m["converged"] for _, _, m in got)
    apart, tied = ({m["result"] for data, _, m in got if ("bridged" in data) == b} for b in (False, True))
    assert apart == {2 * 116} and tied == {2 * 116 - 1}  # components of W2b in FIXTURES.md
