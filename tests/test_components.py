"""Methods, variants and baselines on literal and random graphs, and the invariants of the rounds."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphcc.baselines import star_contraction
from graphcc.baselines.sequential import DisjointSets, union_find
from graphcc.functions.ids import dictionary, digest128, tagged
from graphcc.plans.components import NotConverged, connected_components, spanning_forest
from graphcc.operators.graph_results import diameter_hint
from graphcc.plans.election import choose_strategy, edge_seed, elect_round, largest_group
from graphcc.plans.flatten import canonical, flatten, tree_shape
from graphcc.plans.local_forest import local_forest, local_roots
from graphcc.plans.metrics import Run, doubling_efficiency, local_reduction, observed, partition_profile, prune_rates, speedups
from graphcc.plans.store import RoundStore
from graphcc.schema import canonicalize, dropped_edges
from graphcc.sources import synthetic
from graphcc.sources.workloads import edges as workload
from graphcc.sources.workloads import replicate
from graphcc.streaming.incremental import BANDS, ComponentState, incremental_components, within_bands
from graphcc.streaming.queries import settle


def graph(spark, pairs, parts=None):
    df = spark.createDataFrame([tuple(p) for p in pairs], "u long, v long")
    return df.repartition(parts) if parts else df


def brute(pairs):
    """node -> smallest node of its component, by breadth-first search."""
    near = {}
    for a, b in pairs:
        if a is not None and b is not None and a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    out = {}
    for start in sorted(near):
        if start not in out:
            todo = [start]
            out[start] = start
            while todo:
                for y in near[todo.pop()]:
                    if y not in out:
                        out[y] = start
                        todo.append(y)
    return out


def rows(df):
    got = [(r[0], r[1]) for r in df.collect()]
    assert len(got) == len({n for n, _ in got})
    return dict(got)


R = random.Random(1)
GRAPHS = {
    "empty": [], "self_loop": [(7, 7)], "doubled": [(1, 2), (2, 1), (1, 2)], "nulls": [(None, 1), (2, None), (3, 4)],
    "chain": [(i, i + 1) for i in range(60)], "falling": [(i + 1, i) for i in range(60)], "star": [(0, i) for i in range(1, 80)],
    "clique": [(a, b) for a in range(9) for b in range(a)], "ids": [(-5, 0), (0, 2**63 - 1), (-(2**63), 17)],
    "forest": [(R.randrange(120), R.randrange(120)) for _ in range(90)], "dense": [(R.randrange(50), R.randrange(50)) for _ in range(400)],
}


@pytest.mark.parametrize("name", GRAPHS)
def test_methods_agree_with_breadth_first_search(spark, name):
    e, want = graph(spark, GRAPHS[name], 3), brute(GRAPHS[name])
    for options in ({}, {"method": "sequential"}):
        assert rows(connected_components(e, **options)) == want, options


@pytest.mark.parametrize(
    "options",
    [
        {"method": "lfpe_no_local"}, {"method": "star_contraction"}, {"method": "label_propagation"}, {"method": "graph_library"}, {"emit": "incremental"}, {"election": "max"},
        {"election": "min"}, {"strategy": "window"}, {"strategy": "hub_broadcast", "hub_limit": 3}, {"strategy": "salted", "hub_limit": 3}, {"kernel": "weighted"}, {"max_local_nodes": 7}, {"levels": 2},
        {"tail_rows": 10**6}, {"flatten_method": "min_neighbour"}, {"partitioning": "range", "k": 5}, {"partitioning": "hash", "k": 5}, {"partitioning": "round_robin", "k": 5}, {"method": "lfpe_no_local", "seed": "election"},
        {"method": "star_contraction", "schedule": "inner_fixpoint"}, {"method": "sequential", "weighted": False, "compress": False},
    ],
)
def test_variants(spark, options):
    pairs = GRAPHS["forest"] + [(a + 500, b + 500) for a, b in GRAPHS["star"]] + GRAPHS["ids"] + GRAPHS["nulls"]
    assert rows(connected_components(graph(spark, pairs, 6), **options)) == brute(pairs)


def test_vertices_and_roots(spark):
    e = graph(spark, [(1, 2), (7, 7)])
    alone = spark.createDataFrame([(7,), (2,), (9,), (9,), (None,)], "node long")
    assert rows(connected_components(e, vertices=alone)) == {1: 1, 2: 1, 7: 7, 9: 9}
    assert rows(connected_components(e, include_roots=False)) == {2: 1}
    assert dropped_edges(graph(spark, [(None, 1), (3, 3), (4, 5)])).first().asDict() == {"rows": 3, "null_ends": 1, "self_loops": 1}
    assert {tuple(r) for r in canonicalize(graph(spark, [(2, 1), (1, 2), (3, 3)])).collect()} == {(1, 2)}


def test_sequential_union_find_and_its_ablations():
    chain = [(i, i + 1) for i in range(500)]
    for weighted in (True, False):
        for compress in (True, False):
            got = union_find(chain + [(900, 901)], weighted, compress)
            assert len({got[x] for x in range(501)}) == 1 and got[900] == got[901] != got[0]
    for _ in range(20):
        sets, pairs = DisjointSets(compress=False), [(R.randrange(200), R.randrange(200)) for _ in range(400)]
        for a, b in pairs:
            sets.union(a, b)
        assert sets.depth() <= math.log2(len(sets.parent))
    stick = DisjointSets(weighted=False, compress=False)
    for a, b in reversed(chain):
        stick.union(a, b)
    assert stick.depth() > 100


def test_local_forest_of_one_partition(spark):
    e = graph(spark, [(1, 2), (3, 4), (3, 5), (2, 4)]).coalesce(1)
    got = {tuple(r) for r in local_forest(e, emit="incremental", kernel="weighted").collect()}
    assert got == {(2, 1), (4, 3), (5, 3), (2, 3), (1, 1), (3, 3)}
    star = {tuple(r) for r in local_forest(e, emit="star", kernel="weighted").collect()}
    assert star == {(1, 3), (2, 3), (4, 3), (5, 3), (3, 3)}
    assert {tuple(r) for r in local_forest(e).collect()} == {(2, 1), (3, 1), (4, 1), (5, 1), (1, 1)}


def test_vector_kernel_ignores_order():
    u, v = np.array([5, 3, 9, 8, 2**62]), np.array([3, 4, 8, 1, -7])
    ids, root = local_roots(u, v)
    for _ in range(5):
        p = np.random.default_rng(0).permutation(5)
        again = local_roots(v[p], u[p])
        assert (again[0] == ids).all() and (again[1] == root).all()
    assert dict(zip(ids.tolist(), root.tolist(), strict=True)) == {-7: -7, 1: 1, 3: 3, 4: 3, 5: 3, 8: 1, 9: 1, 2**62: -7}


def test_invariants_of_every_round(spark):
    pairs = GRAPHS["forest"] + GRAPHS["dense"] + [(a + 300, b + 300) for a, b in GRAPHS["chain"]]
    want = brute(pairs)
    for election in ("min", "hash"):
        live = [tuple(r) for r in local_forest(graph(spark, pairs, 4)).distinct().collect()]
        done, r = {}, 0
        while live:
            parents = {p for _, p in live}
            assert all((p, p) in set(live) for p in parents), "a parent is a candidate for itself"
            joined = brute(live + list(done.items()))
            assert all(joined.get(n, n) == want[n] for n in want), "nothing falls apart"
            out = elect_round(spark.createDataFrame(live, "child long, parent long"), election).distinct().collect()
            r += 1
            for x in out:
                if x.kind == "resolved":
                    assert x.child not in done, "finished once"
                    done[x.child] = x.parent
            live = [(x.child, x.parent) for x in out if x.kind == "live"]
        assert len(done) == len(want) - len(set(want.values()))


def test_round_by_round_trace(spark):
    parts = [[(4, 5), (5, 6), (1, 2)], [(2, 3), (6, 7), (8, 9)], [(3, 4), (9, 8), (7, 6)]]
    live = None
    for p in parts:
        pairs = local_forest(graph(spark, p).coalesce(1), kernel="weighted")
        live = pairs if live is None else live.union(pairs)
    run = Run()
    from graphcc.plans.components import resolve

    forest = {(r.child, r.parent, r["round"]) for r in resolve(live, "min", run=run).collect()}
    assert forest == {(5, 4, 1), (9, 8, 2), (6, 4, 3), (7, 4, 3), (4, 3, 4), (3, 2, 5), (2, 1, 6)}
    stars = flatten(spark.createDataFrame([(c, p) for c, p, _ in forest], "child long, parent long"))
    assert rows(canonical(stars)) == {**dict.fromkeys(range(1, 8), 1), 8: 8, 9: 8}


def test_tree_that_a_local_stop_would_leave_unfinished(spark):
    tree = spark.createDataFrame([(2, 1), (3, 1), (0, 2)], "child long, parent long")
    for method in ("doubling", "min_neighbour"):
        assert set(rows(canonical(flatten(tree, method))).values()) == {0}


def test_election_decides_the_rounds_of_a_rising_chain(spark):
    e = graph(spark, [(i, i + 1) for i in range(100)])
    counts = {}
    for election in ("min", "hash"):
        run = Run()
        spanning_forest(e, local=False, election=election, run=run)
        counts[election] = run.rounds()
    assert counts["min"] >= 95 and counts["hash"] <= 4 * math.log2(101)
    with pytest.raises(NotConverged):
        spanning_forest(e, local=False, election="min", max_rounds=5)


def test_records_of_the_local_phase(spark):
    e = graph(spark, [(i, i + 1) for i in range(2000)])
    near, far = Run(), Run()
    spanning_forest(e, k=8, partitioning="range", tail_rows=10**6, run=near)
    spanning_forest(e, k=8, partitioning="round_robin", tail_rows=10**6, run=far)
    assert near.value("local", "pairs") == 2000 and near.value("local", "self_links") <= 8
    assert far.value("local", "pairs") + far.value("local", "self_links") > 3000
    assert local_reduction(near)["pairs"] == 0.5 and local_reduction(near)["with_self_links"] > local_reduction(far)["with_self_links"]


def test_metamorphic(spark):
    pairs = GRAPHS["forest"]
    want = brute(pairs)
    shuffled = [(b, a) if R.random() < 0.5 else (a, b) for a, b in R.sample(pairs, len(pairs))] + pairs[:20]
    assert rows(connected_components(graph(spark, shuffled, 5))) == want
    tops = sorted(set(want.values()))
    bridged = rows(connected_components(graph(spark, pairs + [(tops[0], tops[1])])))
    assert len(set(bridged.values())) == len(tops) - 1
    assert rows(connected_components(replicate(graph(spark, pairs), 2, 1000))) == want | {n + 1000: c + 1000 for n, c in want.items()}
    assert len(set(rows(connected_components(replicate(graph(spark, [(0, 1), (1, 2)]), 4, 100, bridge=True))).values())) == 1


def test_restart_after_a_finished_round(spark, sf):
    e = workload(spark, sf, "w3")
    store = RoundStore(spark)
    with pytest.raises(NotConverged):
        spanning_forest(e, k=8, partitioning="round_robin", store=store, max_rounds=2)
    again = RoundStore(spark, store.path)
    assert again.rounds == [1, 2]
    forest = spanning_forest(e, k=8, partitioning="round_robin", store=again)
    assert forest.count() == 1672 and forest.select("child").distinct().count() == 1672


def test_star_steps(spark):
    e = graph(spark, [(1, 2), (2, 3), (3, 4)])
    assert {tuple(r) for r in star_contraction.large_star(e).collect()} == {(2, 1), (3, 1), (4, 2)}
    assert {tuple(r) for r in star_contraction.small_star(e).collect()} == {(2, 1), (3, 2), (4, 3)}


def test_seed_and_election_order(spark):
    e = graph(spark, [(5, 2), (2, 5), (3, 3)])
    assert {tuple(r) for r in edge_seed(e).collect()} == {(5, 2), (2, 2)}
    most = rows(connected_components(e, method="lfpe_no_local", seed="election", election="max"))
    assert most == {5: 2, 2: 2}


def test_ids(spark):
    df = spark.createDataFrame([("b",), ("a",), ("b",), (None,), ("ü",)], "s string")
    assert {r.s: r.id for r in dictionary(df, "s").collect()} == {"a": 0, "b": 1, "ü": 2}
    r = df.select(digest128(F.col("s")).alias("d"), tagged(F.lit(3), 1).alias("t")).first()
    assert len(r.d) == 16 and r.t == 7


def test_synthetic_source(spark):
    synthetic.register(spark)
    load = lambda **o: spark.read.format("synthetic_graph").options(**o).load()
    assert load(shape="chain", n=50).count() == 50
    assert len(set(rows(connected_components(load(shape="cliques", n=100, clique=20))).values())) == 5
    assert load(shape="star", n=9).where("u = 0").count() == 9 and load(shape="random", n=30).count() == 30


def test_a_round_is_one_exchange_by_child(spark):
    live = local_forest(graph(spark, GRAPHS["dense"], 4))
    from graphcc.session import Kept

    plan = elect_round(Kept(live).df)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(child") <= 2 and "rangepartitioning" not in plan


def test_fingerprint_of_many_large_hashes_does_not_overflow(spark):
    out, seen = observed(spark.range(200_000).selectExpr("id + 9000000000000000000 AS u", "id AS v"), ["u", "v"])
    assert out.count() == 200_000 and seen.get["fingerprint"] != 0
    plain = spark.range(2).selectExpr("9223372036854775807 AS x").agg(F.sum("x"))
    with pytest.raises(Exception, match="OVERFLOW"):  # why it is no sum
        plain.collect()


def test_pruned_flattening_keeps_groups_that_hang_below_others(spark):
    forest = [(5, 4), (6, 4), (4, 2), (3, 2), (2, 1), (20, 10), (21, 10), (31, 30)]
    want = {5: 1, 6: 1, 4: 1, 3: 1, 2: 1, 20: 10, 21: 10, 31: 30}
    df = spark.createDataFrame(forest, "child long, parent long")
    for method in ("doubling", "min_neighbour", "min_neighbour_pruned"):
        run = Run()
        assert rows(flatten(df, method, run)) == want
        if method == "doubling":  # finished pairs do not move again
            assert [run.value("flatten", "records", r) for r in range(1, run.rounds("flatten") + 1)] == [8, 4]
    assert tree_shape(df).first().asDict() == {"nodes": 8, "max_depth": 3, "at_depth_1": 4}


def test_auto_strategy_sets_hubs_apart_only_where_there_are_some(spark):
    star = spark.createDataFrame([(0, i) for i in range(1, 60)] + [(i, i) for i in range(60)], "child long, parent long")
    assert largest_group(star) == 60
    assert choose_strategy(star, None, 59) == "hub_broadcast" and choose_strategy(star, None, 60) == "join" and choose_strategy(star, 50, 50) == "join"
    plan = elect_round(star, strategy="auto", hub_limit=20)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan


def test_prune_rates_and_speedups():
    run = Run()
    run.add("elect", 1, groups=8, resolved=2)
    run.add("elect", 2, groups=4, resolved=4)
    assert prune_rates(run) == {1: 0.25, 2: 1.0}
    assert speedups(100, {"a": 2.0, "b": 5.0}, "a") == [("a", 2.0, 1.0, 50.0), ("b", 5.0, 2.5, 20.0)]
    assert doubling_efficiency([(10, 1.0), (20, 2.0), (40, 2.0)]) == [1.0, 2.0]


def test_partition_profile(spark):
    df = spark.createDataFrame([(i % 3,) for i in range(90)], "g long").repartition(9)
    got = partition_profile(df, "g").first()
    assert (got.partitions, got.mean, got.largest_group) == (9, 10.0, 30) and got.most >= 10


def test_diameter_hint(spark):
    chain, ring = [(i, i + 1) for i in range(7)], [(100 + i, 100 + (i + 1) % 6) for i in range(6)]
    e = graph(spark, chain + ring)
    got = {r.component: r.least_diameter for r in diameter_hint(e, connected_components(e)).collect()}
    assert got == {0: 7, 100: 3}
    with pytest.raises(NotConverged):
        diameter_hint(e, connected_components(e), max_rounds=5)


def test_state_folds_its_folders_and_a_restart_repeats_nothing(spark, tmp_path):
    state, pairs = ComponentState(spark, str(tmp_path / "state")), []
    for b in range(5):
        batch = [(b * 10 + i, b * 10 + i + 1) for i in range(3)] + ([(b * 10, b * 10 - 7)] if b else [])
        pairs += batch
        state.apply(graph(spark, batch), b)
        if b == 3:
            state.fold(2)
            state.apply(graph(spark, batch), b)  # a batch once more
    assert len(state._node_folders(4)) == 3 and rows(state.components()) == brute(pairs)


def test_a_batch_looks_its_nodes_up_by_ranges(spark, tmp_path):
    path, far = str(tmp_path / "nodes"), 2**62
    ids = [-far, -7, 0, 5, 6, 1000, far]
    spark.createDataFrame([(i, i) for i in [*ids, -8, 7, 2000]], "node long, root long").write.parquet(path)
    nodes = spark.read.schema("node long, root long").parquet(path)
    near = within_bands(nodes, spark.createDataFrame([(5,), (6,), (5,)], "node long"))
    assert {r.node for r in near.collect()} == {5, 6}
    plan = near._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(node,5)" in plan.split("PushedFilters")[1]
    assert set(ids) <= {r.node for r in within_bands(nodes, spark.createDataFrame([(i,) for i in ids], "node long")).collect()}
    wide = within_bands(nodes, spark.range(0, 10 * BANDS).select(F.col("id").alias("node")))
    assert {r.node for r in wide.collect()} == {0, 5, 6, 7}
    assert within_bands(nodes, spark.createDataFrame([], "node long")).isEmpty()


def test_stream_restarts_from_its_checkpoint(spark, tmp_path):
    source, checkpoint, state = str(tmp_path / "in"), str(tmp_path / "checkpoint"), str(tmp_path / "state")
    graph(spark, [(1, 2), (5, 6)]).coalesce(1).write.parquet(source)
    for more in ([], [(2, 5)], [(9, 10)]):
        if more:
            graph(spark, more).coalesce(1).write.mode("append").parquet(source)
        stream = spark.readStream.schema("u long, v long").parquet(source)
        incremental_components(stream, state, checkpoint).awaitTermination()
    assert rows(ComponentState(spark, state).components()) == {1: 1, 2: 1, 5: 1, 6: 1, 9: 9, 10: 9}
    assert ComponentState(spark, state)._versions()[-1] == 2


def test_late_rows_are_dropped_behind_the_watermark(spark, tmp_path):
    source = str(tmp_path / "in")
    for i, ts in enumerate(["2024-01-01 00:00:10", "2024-01-01 05:00:00", "2024-01-01 05:30:00", "2024-01-01 00:00:20", "2024-01-01 09:00:00"]):
        spark.createDataFrame([(i, ts)], "id long, t string").selectExpr("id", "CAST(t AS timestamp) AS ts").coalesce(1).write.mode("append").parquet(source)
    stream = spark.readStream.schema("id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(source)
    per = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    got = {r.window.start.hour: r.n for r in settle(per).collect()}
    assert got == {0: 1, 5: 2}  # the second row of hour 0 came five hours late
