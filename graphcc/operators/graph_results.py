"""What a user asks of components: sizes, large ones, members, quotient graphs, profiles, splitting at hubs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.plans.components import NotConverged, connected_components
from graphcc.plans.metrics import observed
from graphcc.session import Kept, computed_at_once, scratch_path

LCC_NODES = 5000


def component_sizes(stars: DataFrame) -> DataFrame:
    return stars.groupBy("component").agg(F.count(F.lit(1)).alias("nodes"))


def lcc_report(stars: DataFrame, threshold: int = LCC_NODES) -> DataFrame:
    """One row: components, the largest, how many exceed ``threshold`` nodes."""
    return component_sizes(stars).agg(
        F.count(F.lit(1)).alias("components"), F.max("nodes").alias("largest"), F.sum((F.col("nodes") > threshold).cast("long")).alias("large"), F.sum("nodes").alias("nodes")
    )


def size_histogram(stars: DataFrame) -> DataFrame:
    """Components by power-of-two size bands: band b holds sizes from 2**b to 2**(b+1) - 1."""
    band = F.floor(F.log2(F.col("nodes") + 0.0)).cast("long").alias("band")
    return component_sizes(stars).groupBy(band).agg(F.count(F.lit(1)).alias("components"), F.sum("nodes").alias("nodes"))


def members(stars: DataFrame, component: int) -> DataFrame:
    return stars.where(F.col("component") == component).select("node")


def same_component(stars: DataFrame, pairs: DataFrame) -> DataFrame:
    """``(a, b, same)`` for pairs of nodes; false if either has no component."""
    one, two = stars.select(F.col("node").alias("a"), F.col("component").alias("ca")), stars.select(F.col("node").alias("b"), F.col("component").alias("cb"))
    return pairs.join(one, "a", "left").join(two, "b", "left").select("a", "b", F.coalesce(F.col("ca") == F.col("cb"), F.lit(False)).alias("same"))


def contract(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """The quotient graph: distinct edges between different labels of ``(node, component)``; unlabelled nodes stand for themselves."""
    one, two = labels.select(F.col("node").alias("u"), F.col("component").alias("cu")), labels.select(F.col("node").alias("v"), F.col("component").alias("cv"))
    ends = edges.join(one, "u", "left").join(two, "v", "left").select(F.coalesce("cu", "u").alias("x"), F.coalesce("cv", "v").alias("y"))
    return ends.where("x <> y").select(F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v")).distinct()


def induced(edges: DataFrame, stars: DataFrame, component: int) -> DataFrame:
    """Edges inside one component."""
    return edges.join(members(stars, component).withColumnRenamed("node", "u"), "u", "left_semi").select("u", "v")


def degree(edges: DataFrame) -> DataFrame:
    """Distinct neighbours of each node."""
    both = edges.where("u <> v").select("u", "v").union(edges.where("u <> v").select("v", "u")).distinct()
    return both.groupBy(F.col("u").alias("node")).agg(F.count(F.lit(1)).alias("degree"))


def graph_profile(edges: DataFrame, stars: DataFrame, threshold: int = LCC_NODES) -> DataFrame:
    """One row for a graph: size, density, largest degree and component, and its class.

    a sparse: small components, few edges a node; b dense: more than 4 edges a node; c chain: no node
    has more than two neighbours; d: a component above ``threshold`` nodes.
    """
    deg = degree(edges).agg(F.count(F.lit(1)).alias("nodes"), (F.sum("degree") / 2).cast("long").alias("edges"), F.max("degree").alias("max_degree"))
    kind = F.when(F.col("largest") > threshold, "d").when(F.col("edges") > 4 * F.col("nodes"), "b").when(F.col("max_degree") <= 2, "c").otherwise("a")
    report = lcc_report(stars, threshold).drop("nodes")
    return deg.crossJoin(report).withColumn("class", kind)  # one row each


def split_lcc(edges: DataFrame, max_degree: int, **options) -> DataFrame:
    """Components after nodes with more than ``max_degree`` neighbours are taken out; those are absent from the result."""
    hubs = degree(edges).where(F.col("degree") > max_degree).select("node")
    left = edges.join(hubs.withColumnRenamed("node", "u"), "u", "left_anti").join(hubs.withColumnRenamed("node", "v"), "v", "left_anti")
    return connected_components(left, **options)


def diameter_hint(edges: DataFrame, stars: DataFrame, max_rounds: int = 1000) -> DataFrame:
    """``(component, least_diameter)``: the farthest any node lies from the smallest one, by a breadth-first walk of all components at once.

    A component's diameter is that at least, and twice that at most. Only the last step's nodes meet the edges, and what
    they reach is new unless it lies in that step or the one before. Raises NotConverged after ``max_rounds`` steps.
    """
    e, spark = edges.where("u <> v"), edges.sparkSession
    both = Kept(e.select("u", "v").union(e.select("v", "u")).distinct(), "both")
    path, shape = scratch_path(spark, "steps"), "node long, component long, step int"

    def step_of(n: int) -> DataFrame:
        return spark.read.schema(shape).parquet(f"{path}/{n}")

    stars.where("node = component").select("node", "component", F.lit(0).alias("step")).write.parquet(f"{path}/0")
    for n in range(1, max_rounds + 1):
        front = step_of(n - 1)
        near = front if n == 1 else front.unionByName(step_of(n - 2))
        reached = both.df.join(front, F.col("u") == front.node).select(F.col("v").alias("node"), "component").distinct()
        new, seen = observed(reached.join(near.select("node"), "node", "left_anti").withColumn("step", F.lit(n)))
        with computed_at_once(spark):
            new.write.parquet(f"{path}/{n}")
        if not seen.get["n"]:
            break
    else:
        raise NotConverged(f"some component reaches farther than {max_rounds} steps")
    both.drop()
    return spark.read.schema(shape).parquet(f"{path}/*").groupBy("component").agg(F.max("step").cast("long").alias("least_diameter"))
