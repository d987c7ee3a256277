"""Phase 2, one round: all candidates of a child meet, one is elected, finished nodes leave.

A round is one exchange by child. The state of a child is a pair of aggregates, never a
list, so a child with billions of candidates costs no more memory than any other. Where a child has
more than ``hub_limit`` candidates, they are not brought into one task either: ``auto`` finds that out first.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

ELECTIONS, STRATEGIES = ("min", "max", "hash"), ("auto", "join", "window", "hub_broadcast", "salted")


def preference(parent: Column, election: str) -> Column:
    """What the elected candidate has the least of."""
    if election == "min":
        return parent
    if election == "max":
        return F.bitwise_not(parent)  # reverses the order, without overflow at either end of the range
    if election == "hash":
        return F.struct(F.xxhash64(parent), parent)
    raise ValueError(f"unknown election {election!r}")


def edge_seed(edges: DataFrame, seed: str = "min_id", election: str = "hash") -> DataFrame:
    """Live pairs without a local phase: each edge gives a parent pair and the parent's self-link."""
    if seed == "min_id":
        lo, hi = F.least("u", "v"), F.greatest("u", "v")
    else:
        first = preference(F.col("u"), election) <= preference(F.col("v"), election)
        lo, hi = F.when(first, F.col("u")).otherwise(F.col("v")), F.when(first, F.col("v")).otherwise(F.col("u"))
    pairs = F.array(F.struct(hi.alias("child"), lo.alias("parent")), F.struct(lo.alias("child"), lo.alias("parent")))
    return edges.where("u <> v").select(F.inline(pairs))


def _judged(live: DataFrame, election: str, strategy: str, hub_limit: int) -> DataFrame:
    """Distinct live pairs with the elected parent (``winner``) and whether there was a choice (``many``)."""
    rank = preference(F.col("parent"), election)
    summary = [F.min_by("parent", rank).alias("winner"), (F.min("parent") != F.max("parent")).alias("many")]
    if strategy in ("join", "window"):
        pairs = live.repartition("child").dropDuplicates(["child", "parent"])
        if strategy == "join":
            return pairs.join(pairs.groupBy("child").agg(*summary), "child")
        by = Window.partitionBy("child")
        return pairs.withColumn("winner", F.min_by("parent", rank).over(by)).withColumn("many", F.min("parent").over(by) != F.max("parent").over(by))
    pairs = live.dropDuplicates(["child", "parent"])
    counted = live.groupBy("child").agg(*summary, F.count(F.lit(1)).alias("n"))  # partially aggregated before its exchange
    if strategy == "hub_broadcast":
        # At most |live| / hub_limit children are hubs, and only these few winners are broadcast.
        hubs, rest = counted.where(F.col("n") > hub_limit).drop("n"), counted.where(F.col("n") <= hub_limit).drop("n")
        of_hubs = pairs.join(F.broadcast(hubs), "child")
        return of_hubs.unionByName(pairs.join(F.broadcast(hubs.select("child")), "child", "left_anti").join(rest, "child"))
    if strategy == "salted":
        salts = (F.col("n") / hub_limit).cast("int") + 1
        most = F.greatest(F.lit(1), F.least(F.lit(64), salts))
        spread = counted.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(63)))).where((F.col("salt") < most) | (F.col("n") > hub_limit))
        small, large = counted.where(F.col("n") <= hub_limit).withColumn("salt", F.lit(0)), spread.where(F.col("n") > hub_limit)
        hubs = F.broadcast(large.select("child").distinct().withColumn("hub", F.lit(True)))
        dealt = pairs.join(hubs, "child", "left").withColumn("salt", F.when(F.col("hub"), F.pmod(F.xxhash64("parent"), F.lit(64)).cast("int")).otherwise(F.lit(0)))
        return dealt.join(small.unionByName(large).drop("n"), ["child", "salt"]).select("child", "parent", "winner", "many")
    raise ValueError(f"unknown strategy {strategy!r}")


def largest_group(live: DataFrame) -> int:
    """Candidates of the child with most of them, counted on the map side first."""
    return live.groupBy("child").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0


def choose_strategy(live: DataFrame, rows: int | None, hub_limit: int) -> str:
    """One plain exchange while no child can have, or has, more than ``hub_limit`` candidates; else hubs apart."""
    safe = rows is not None and rows <= hub_limit or largest_group(live) <= hub_limit
    return "join" if safe else "hub_broadcast"


def elect_round(
    live: DataFrame, election: str = "hash", strategy: str = "auto", hub_limit: int = 1_000_000, rows: int | None = None, seen: Observation | None = None
) -> DataFrame:
    """``(kind, child, parent)``: kind 'resolved' leaves for good, kind 'live' goes on. ``seen`` gets the number of children.

    A child that met only itself disappears. One foreign parent: the pair is resolved. Several:
    every candidate, and the child, get the winner as parent; (winner, winner) renews its self-link.
    """

    def row(kind: str, child: str, parent: str):
        return F.struct(F.lit(kind).alias("kind"), F.col(child).alias("child"), F.col(parent).alias("parent"))

    follow = F.when((F.col("parent") == F.col("winner")) & (F.col("child") != F.col("winner")), F.array(row("live", "parent", "winner"), row("live", "child", "winner")))
    out = F.when(F.col("many"), follow.otherwise(F.array(row("live", "parent", "winner")))).when(F.col("parent") != F.col("child"), F.array(row("resolved", "child", "parent")))
    judged = _judged(live, election, choose_strategy(live, rows, hub_limit) if strategy == "auto" else strategy, hub_limit)
    if seen is not None:  # one row of each child has the winner
        judged = judged.observe(seen, F.coalesce(F.sum((F.col("parent") == F.col("winner")).cast("long")), F.lit(0)).alias("groups"))
    return judged.select(F.inline(out))
