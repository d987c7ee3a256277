"""Connected components end to end, and the loop of election rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from graphcc.plans.election import edge_seed, elect_round
from graphcc.plans.flatten import canonical, flatten
from graphcc.plans.local_forest import MAX_LOCAL_NODES, _kernel, local_forest, place, second_level
from graphcc.plans.metrics import Run, observed
from graphcc.plans.store import RoundStore
from graphcc.schema import check_edges, nodes_of


class NotConverged(RuntimeError):
    """Live rows were left after ``max_rounds``: what a benchmark table prints as N/A."""


def resolve(
    live: DataFrame, election: str = "hash", strategy: str = "auto", store: RoundStore | None = None, max_rounds: int = 200, tail_rows: int = 0, hub_limit: int = 1_000_000, run: Run | None = None, rows: int | None = None
) -> DataFrame:
    """Election rounds until no row is live; the forest ``(child, parent, round)``.

    ``live`` is what phase 1 gave, already materialised or cheap to compute, ``rows`` its size if known. Fewer
    than ``tail_rows`` live rows are finished in one task, whose size that number bounds.
    """
    run = run or Run()
    store = store or RoundStore(live.sparkSession)
    r = len(store.rounds)
    n = store.live(r).count() if r else None
    while n is None or n > 0:
        now = store.live(r) if r else live
        r += 1
        if r > max_rounds:
            run.converged = False
            raise NotConverged(f"{n} live rows after {max_rounds} rounds")
        if n is not None and n < tail_rows:
            tail = now.select(F.col("child").alias("u"), F.col("parent").alias("v")).coalesce(1).mapInArrow(_kernel("star", "vector", MAX_LOCAL_NODES, False), "child long, parent long")
            judged, groups = tail.where("child <> parent").select(F.lit("resolved").alias("kind"), "child", "parent"), None
        else:
            groups = Observation()
            judged = elect_round(now, election, strategy, hub_limit, rows if n is None else n, groups)
        is_live = F.col("kind") == "live"
        out, seen = observed(judged, live=is_live, loops=is_live & (F.col("child") == F.col("parent")))
        with run.timed("elect", r):
            store.write(r, out)
        got = seen.get
        if groups is not None:
            run.add("elect", r, groups=groups.get["groups"])
        run.add("elect", r, records=n or rows or 0, resolved=got["n"] - got["live"], live=got["live"], self_links=got["loops"])
        n = got["live"]
    return store.forest()


def spanning_forest(
    edges: DataFrame, local: bool = True, k: int | None = None, partitioning: str = "input", emit: str = "star", kernel: str = "vector", levels: int = 1,
    max_local_nodes: int | None = MAX_LOCAL_NODES, seed: str = "min_id", election: str = "hash", strategy: str = "auto", max_rounds: int = 200, tail_rows: int = 0,
    hub_limit: int = 1_000_000, store: RoundStore | None = None, run: Run | None = None,
) -> DataFrame:
    """Phases 1 and 2: one parent for every node that is not a root, as ``(child, parent, round)``."""
    run = run or Run()
    store = store or RoundStore(edges.sparkSession)
    if store.rounds:  # a restart: phase 1 and the finished rounds are on disk
        return resolve(store.live(0), election, strategy, store, max_rounds, tail_rows, hub_limit, run)
    e = check_edges(edges)
    counted, seen_in = observed(place(e, partitioning, k) if local else e)  # after placing: cutting ranges reads its input twice
    if local:
        pairs = local_forest(counted, emit=emit, kernel=kernel, max_local_nodes=max_local_nodes)
        pairs = second_level(pairs, max_local_nodes=max_local_nodes) if levels == 2 else pairs
    else:
        pairs = edge_seed(counted, seed, election)
    out, seen = observed(pairs, loops=F.col("child") == F.col("parent"))
    with run.timed("local"):
        live = store.seed(out)
    run.add("input", 0, edges=seen_in.get["n"])
    run.add("local", 0, pairs=seen.get["n"] - seen.get["loops"], self_links=seen.get["loops"])
    return resolve(live, election, strategy, store, max_rounds, tail_rows, hub_limit, run, seen.get["n"])


def connected_components(
    edges: DataFrame, method: str = "lfpe", output: str = "stars", vertices: DataFrame | None = None, include_roots: bool = True, flatten_method: str = "doubling", run: Run | None = None, **options
) -> DataFrame:
    """``(node, component)``, component being the smallest node id of each component.

    Methods: ``lfpe`` (local forests, then parent election), ``lfpe_no_local``, ``star_contraction``,
    ``label_propagation``, ``graph_library`` (the JVM library's routine, to compare with), ``sequential`` and
    ``recursive_sql`` (small inputs). ``output='forest'`` of the first two returns the spanning forest instead.
    ``vertices(node)`` adds nodes without an edge.
    """
    from graphcc.baselines import graph_library, label_propagation, recursive_sql, star_contraction
    from graphcc.baselines.driver_side import sequential_components

    run = run or Run(method)
    if method in ("lfpe", "lfpe_no_local"):
        forest = spanning_forest(edges, local=method == "lfpe", run=run, **options)
        if output == "forest":
            return forest
        result = canonical(flatten(forest, flatten_method, run))
    elif method == "star_contraction":
        result = star_contraction.components(check_edges(edges), run=run, **options)
    elif method == "label_propagation":
        result = label_propagation.components(check_edges(edges), run=run, **options)
    elif method == "graph_library":
        result = graph_library.components(check_edges(edges), run=run, **options)
    elif method == "sequential":
        result = sequential_components(check_edges(edges), **options)
    elif method == "recursive_sql":
        result = recursive_sql.components(check_edges(edges), **options)
    else:
        raise ValueError(f"unknown method {method!r}")
    if not include_roots:
        result = result.where("node <> component")
    if vertices is not None:
        alone = vertices.select(F.col("node").cast("long").alias("node")).where("node IS NOT NULL").distinct().join(result.select("node"), "node", "left_anti")
        result = result.unionByName(alone.withColumn("component", F.col("node")))
    return result


__all__ = ["NotConverged", "connected_components", "nodes_of", "resolve", "spanning_forest"]
