"""The comparisons of the method with its baselines and of its options, as tables.

``python -m graphcc.experiments [sf_dir] [sizes|local|partitions|election|output]`` prints Markdown rows. What
is measured: wall time, rounds, records moved, and whether a method converged (N/A if not).
"""

from __future__ import annotations

import sys
import time
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

from graphcc.plans.components import NotConverged, connected_components
from graphcc.plans.metrics import Run, local_reduction
from graphcc.session import Kept
from graphcc.sources.workloads import edges, replicate

STRIDE = 4_000_000
METHODS = {
    "star contraction": {"method": "star_contraction"}, "without local forests": {"method": "lfpe_no_local"}, "local forests, then election": {"method": "lfpe"},
    "label propagation": {"method": "label_propagation"}, "graph library": {"method": "graph_library"},
}


def measure(e: DataFrame, **options) -> dict:
    """One run over materialised edges: seconds, rounds, records, components; ``converged`` is False for N/A."""
    run = Run()
    began = time.perf_counter()
    try:
        components = connected_components(e, run=run, **options)
        rows = components.where("node = component").count() if options.get("output") != "forest" else components.count()
    except NotConverged:
        return {"converged": False, "seconds": time.perf_counter() - began}
    phases = ("elect", "large", "small", "propagate")
    return {
        "converged": True, "seconds": time.perf_counter() - began, "rounds": max(run.rounds(p) for p in phases), "flatten_rounds": run.rounds("flatten"),
        "records": run.value("elect", "live") + run.value("elect", "resolved") + sum(run.value(p, "records") for p in phases[1:]), "result": rows, "local_seconds": run.value("local", "seconds"), **local_reduction(run),
    }


def sized(spark: SparkSession, sf_dir: str, copies: int, workload: str = "w3", bridge: bool = False) -> DataFrame:
    """A workload's graph ``copies`` times over, tied together with ``bridge``; the order-part graph has about 0.6 million edges a copy at sf0.1."""
    return Kept(replicate(edges(spark, sf_dir, workload), copies, STRIDE, bridge).repartition(max(8, copies * 2)), "edges").df


def sizes(spark: SparkSession, d: str, copies=(1, 2, 17), workloads=("w1", "w2b", "w3", "w9")) -> Iterator[tuple]:
    for w in workloads:
        for c in copies:
            for bridge in (False, True)[: 1 + (c > 1)]:
                e = sized(spark, d, c, w, bridge)
                n = e.count()
                for name, options in METHODS.items():
                    yield f"{w}{' bridged' * bridge}, {n} edges", name, measure(e, **options)


def local(spark: SparkSession, d: str) -> Iterator[tuple]:
    for w in ("w1", "w2b", "w3", "w4", "w5", "w6", "w6b", "w7", "w8", "w9"):
        e = Kept(edges(spark, d, w), "edges").df
        for name in ("lfpe", "lfpe_no_local"):
            yield w, name, measure(e, method=name)


def partitions(spark: SparkSession, d: str) -> Iterator[tuple]:
    for w in ("w3", "w6", "w4"):
        e = Kept(edges(spark, d, w), "edges").df
        for placement in ("range", "hash", "round_robin"):
            for k in (1, 4, 16, 64):
                yield w, f"{placement} k={k}", measure(e, k=k, partitioning=placement)


def election(spark: SparkSession, d: str) -> Iterator[tuple]:
    for w in ("w6", "w8", "w7"):
        e = Kept(edges(spark, d, w), "edges").df
        for rule in ("min", "max", "hash"):
            yield w, rule, measure(e, method="lfpe_no_local", election=rule, max_rounds=150)


def output(spark: SparkSession, d: str) -> Iterator[tuple]:
    for w in ("w3", "w9"):
        e = Kept(edges(spark, d, w), "edges").df
        for kind in ("forest", "stars"):
            yield w, kind, measure(e, output=kind)


EXPERIMENTS = {f.__name__: f for f in (sizes, local, partitions, election, output)}


def main() -> None:
    sf_dir = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01"
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in sys.argv[2:] or EXPERIMENTS:
        print(f"\n### {name}\n| input | setting | seconds | rounds | records | local reduction |\n| --- | --- | --- | --- | --- | --- |")
        for data, setting, m in EXPERIMENTS[name](spark, sf_dir):
            print(f"| {data} | {setting} | " + (f"{m['seconds']:.1f} | {m['rounds']} | {m['records']:.0f} | {m['with_self_links']:.2f} |" if m["converged"] else "N/A | - | - | - |"), flush=True)


if __name__ == "__main__":
    main()
