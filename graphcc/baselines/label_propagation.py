"""Smallest-label propagation: each node sends its smallest known id to its neighbours until none improves.

The DataFrame form of the components routine of Spark's graph library; rounds grow with the diameter.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.plans.metrics import Run, observed
from graphcc.session import Kept


def components(edges: DataFrame, max_rounds: int = 100, run: Run | None = None) -> DataFrame:
    run = run or Run("label_propagation")
    e = edges.where("u <> v")
    both = Kept(e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct(), "both")
    kept = Kept(both.df.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("label")).select(F.col("u").alias("node"), "label"), "labels")
    for r in range(1, max_rounds + 1):
        offers = both.df.join(kept.df, F.col("u") == F.col("node")).groupBy("v").agg(F.min("label").alias("offer"))
        joined = kept.df.join(offers, F.col("node") == F.col("v"), "left")
        out, seen = observed(joined.select("node", F.least("label", "offer").alias("label"), (F.col("offer") < F.col("label")).alias("c")), changed=F.col("c"))
        with run.timed("propagate", r):
            new = Kept(out.drop("c"), "labels")
        run.add("propagate", r, changed=seen.get["changed"], records=seen.get["n"])
        kept.drop()
        kept = new
        if not seen.get["changed"]:
            both.drop()
            return kept.df.select("node", F.col("label").alias("component"))
    run.converged = False
    from graphcc.plans.components import NotConverged

    raise NotConverged(f"labels still change after {max_rounds} rounds")
