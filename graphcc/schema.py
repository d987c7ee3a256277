"""The edge contract: two LONG columns u and v, checked at the boundary."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def check_edges(edges: DataFrame) -> DataFrame:
    """``(u, v)`` as LONG; rows with a null end are dropped (see ``dropped_edges``)."""
    missing = {"u", "v"} - set(edges.columns)
    if missing:
        raise ValueError(f"edges need columns u and v, missing: {sorted(missing)}")
    return edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).where("u IS NOT NULL AND v IS NOT NULL")


def dropped_edges(edges: DataFrame) -> DataFrame:
    """How many rows a null end disqualifies, how many are self-loops."""
    return edges.agg(
        F.count(F.lit(1)).alias("rows"),
        F.sum((F.col("u").isNull() | F.col("v").isNull()).cast("long")).alias("null_ends"),
        F.sum((F.col("u") == F.col("v")).cast("long")).alias("self_loops"),
    )


def canonicalize(edges: DataFrame) -> DataFrame:
    """Distinct unordered edges, smaller end first, without self-loops."""
    e = check_edges(edges)
    return e.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()


def nodes_of(edges: DataFrame) -> DataFrame:
    """Distinct ``node`` values at either end."""
    return edges.select(F.explode(F.array("u", "v")).alias("node")).distinct()
