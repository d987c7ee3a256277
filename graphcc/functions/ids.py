"""Node identifiers: tags for bipartite graphs, dictionaries for values, wide digests."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphcc.session import keep


def tagged(id_: Column, tag: int, kinds: int = 2) -> Column:
    """Ids of several kinds of nodes in one range: ``id * kinds + tag``."""
    return id_.cast("long") * kinds + tag


def dictionary(values: DataFrame, column: str) -> DataFrame:
    """``(column, id)``: distinct values numbered 0.. in their order, without one global sort task.

    Values are range-sorted over partitions; only one count per partition is summed up.
    """
    ranged = values.select(column).where(F.col(column).isNotNull()).distinct().repartitionByRange(column).sortWithinPartitions(column)
    kept = keep(ranged.select(column, F.spark_partition_id().alias("part")), "values")
    # Equal partition number: a contiguous range of values, so ranks inside a part add to what lies before it.
    counts = kept.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = counts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("first"))
    inside = kept.withColumn("rank", F.row_number().over(Window.partitionBy("part").orderBy(column)))
    return inside.join(F.broadcast(before), "part").select(column, (F.col("first") + F.col("rank") - 1).cast("long").alias("id"))


def digest128(value: Column) -> Column:
    """A 128-bit key for strings: 64 bits would merge components at tens of billions of nodes."""
    return F.unhex(F.md5(value.cast("binary")))
