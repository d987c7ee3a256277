"""Phase 3: trees to stars, and the canonical label of each component."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.plans.metrics import Run, observed
from graphcc.session import Kept, remove


def flatten(forest: DataFrame, method: str = "doubling", run: Run | None = None, max_rounds: int = 64) -> DataFrame:
    """``(node, component)`` for each child of the forest, its parent replaced by its root."""
    run, pairs = run or Run(), forest.select("child", "parent")
    if method == "doubling":
        return depths(pairs, run, max_rounds).select("node", "component")
    if method in ("min_neighbour", "min_neighbour_pruned"):
        return _min_neighbour(pairs, run, max_rounds, method == "min_neighbour_pruned")
    raise ValueError(f"unknown method {method!r}")


def depths(forest: DataFrame, run: Run | None = None, max_rounds: int = 64) -> DataFrame:
    """``(node, component, depth)``: root of each child of the forest, and steps up to it, by pointer doubling.

    A pair known to end at a root is done: it is written once, and is only looked up from then on. So the roots, the hot
    keys of large components, are looked for in the first two rounds alone, in outer joins that the planner may split.
    """
    run = run or Run()
    unsure = forest.select("child", "parent", F.lit(1).cast("long").alias("hops"), F.lit(False).alias("done"))
    everything, finished, kept = unsure, None, None
    for r in range(1, max_rounds + 1):
        up = everything.select(F.col("child").alias("at"), F.col("parent").alias("above"), F.col("hops").alias("more"), F.col("done").alias("ends"))
        met = unsure.join(up, F.col("parent") == F.col("at"), "left")
        moved = met.select(
            "child", F.coalesce("above", "parent").alias("parent"), (F.col("hops") + F.coalesce("more", F.lit(0))).alias("hops"),
            F.coalesce("ends", F.lit(True)).alias("done"), F.col("at").isNotNull().alias("m"),
        )
        out, seen = observed(moved, moved=F.col("m"), finished=F.col("done"))
        with run.timed("flatten", r):
            new = Kept(out.drop("m"), "stars", partition_by=["done"])
        run.add("flatten", r, moved=seen.get["moved"], records=seen.get["n"], finished=seen.get["finished"])
        if kept:
            remove(kept.spark, f"{kept.path}/done=false")
        ready = new.df.where("done")
        finished = finished.unionByName(ready) if finished is not None else ready
        kept, unsure = new, new.df.where("NOT done")
        if seen.get["finished"] == seen.get["n"]:
            break
        everything = finished.unionByName(unsure)
    return finished.unionByName(unsure).select(F.col("child").alias("node"), F.col("parent").alias("component"), F.col("hops").alias("depth"))


def tree_shape(forest: DataFrame, run: Run | None = None) -> DataFrame:
    """One row: nodes that are no roots, the deepest, and how many hang at their root before anything is flattened."""
    at_root = F.sum((F.col("depth") == 1).cast("long"))
    return depths(forest, run).agg(F.count(F.lit(1)).alias("nodes"), F.max("depth").alias("max_depth"), F.coalesce(at_root, F.lit(0)).alias("at_depth_1"))


def _both_ends(pairs: DataFrame) -> DataFrame:
    return pairs.select("child", "parent").union(pairs.select(F.col("parent").alias("child"), F.col("child").alias("parent"))).distinct()


def _whole_stars(both: DataFrame) -> DataFrame:
    """``(child, parent)`` of finished components: all neighbours of the centre are larger and have no other neighbour."""
    per = both.groupBy("child").agg(F.count(F.lit(1)).alias("n"), F.min("parent").alias("least"))
    leaves = per.where((F.col("n") == 1) & (F.col("least") < F.col("child"))).select("child", F.col("least").alias("parent"))
    hung = leaves.groupBy("parent").agg(F.count(F.lit(1)).alias("hung"))
    centres = per.where(F.col("least") > F.col("child")).join(hung, F.col("child") == F.col("parent")).where("n = hung").select("parent")
    return leaves.join(centres, "parent", "left_semi").select("child", "parent")


def _min_neighbour(pairs: DataFrame, run: Run, max_rounds: int, prune: bool = False) -> DataFrame:
    """Every node knows its pairs from both ends and links all neighbours to the smallest, until nothing changes.

    Stops on a global test: that all pairs of one group touch its minimum does not say the group is finished, as it
    may still hang below another. With ``prune``, components leave once they are stars as a whole, which does.
    """
    current, kept, done = pairs.distinct(), None, None
    for r in range(1, max_rounds + 1):
        both = _both_ends(current)
        least = both.groupBy("child").agg(F.least(F.min("parent"), F.first("child")).alias("least"))
        linked = both.join(least, "child").select(F.explode(F.array("child", "parent")).alias("node"), "least").where("node <> least").distinct()
        out, seen = observed(linked.select(F.col("node").alias("child"), F.col("least").alias("parent")), ["child", "parent"])
        with run.timed("flatten", r):
            new = Kept(out, "links")
        state = (seen.get["n"], seen.get["fingerprint"])
        run.add("flatten", r, records=seen.get["n"])
        if kept:
            kept.drop()
        current, kept = new.df, new
        if r > 1 and state == before:
            break
        before = state
        if prune:
            stars = Kept(_whole_stars(_both_ends(current)), "stars").df
            done = stars if done is None else done.unionByName(stars)
            left = Kept(current.join(stars.select(F.col("parent").alias("c")), F.col("parent") == F.col("c"), "left_anti"), "links")
            kept.drop()
            current, kept = left.df, left
            if current.isEmpty():
                break
    rest = current.groupBy("child").agg(F.min("parent").alias("component")).withColumnRenamed("child", "node")
    return rest if done is None else rest.unionByName(done.select(F.col("child").alias("node"), F.col("parent").alias("component")))


def canonical(stars: DataFrame) -> DataFrame:
    """Label every component with its smallest node; roots are added as members of their own.

    Few labels meet many members here, so a large component is a hot key of one plain join, which the planner
    may broadcast or split.
    """
    per = stars.groupBy("component").agg(F.least(F.min("node"), F.col("component")).alias("least"))
    members = stars.join(per, "component").select("node", F.col("least").alias("component"))
    return members.union(per.select(F.col("component").alias("node"), F.col("least").alias("component")))
