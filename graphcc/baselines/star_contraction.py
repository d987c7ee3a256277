"""Alternating star contraction, from the public MapReduce literature.

Large step: every node links its strictly larger neighbours to the smallest node of its
neighbourhood, itself included. Small step: every node links its smaller neighbours and itself
to the smallest of them. Both keep connectivity; at the fix point the pairs are stars.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.plans.metrics import Run, observed
from graphcc.session import Kept


def large_star(pairs: DataFrame) -> DataFrame:
    """One large step over ``(u, v)``; both ends of each pair travel."""
    both = pairs.select("u", "v").union(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def small_star(pairs: DataFrame) -> DataFrame:
    """One small step over ``(u, v)``; a pair travels to its larger end."""
    down = pairs.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v")
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def components(edges: DataFrame, schedule: str = "alternate", max_rounds: int = 100, run: Run | None = None) -> DataFrame:
    """``(node, component)``; ``schedule`` is ``alternate`` or ``inner_fixpoint`` (large steps until stable, then a small one)."""
    run = run or Run("star_contraction")
    kept: Kept | None = None
    pairs, seen_before, r = edges.where("u <> v"), None, 0

    def turn(step, phase: str) -> tuple[int, int]:
        nonlocal kept, pairs, r
        r += 1
        if r > max_rounds:
            run.converged = False
            from graphcc.plans.components import NotConverged

            raise NotConverged(f"no fix point after {max_rounds} steps")
        out, seen = observed(step(pairs), ["u", "v"])
        with run.timed(phase, r):
            new = Kept(out, "pairs")
        run.add(phase, r, records=seen.get["n"])
        if kept:
            kept.drop()
        kept, pairs = new, new.df
        return seen.get["n"], seen.get["fingerprint"]

    while True:
        if schedule == "inner_fixpoint":
            inner = None
            while (now := turn(large_star, "large")) != inner:
                inner = now
        else:
            turn(large_star, "large")
        state = turn(small_star, "small")
        if state == seen_before:
            break
        seen_before = state
    star = pairs.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return star.union(star.select("component", "component").distinct())
