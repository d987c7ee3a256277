"""The components routine of Spark's own graph library, which has a JVM interface only.

Edges go to it as a text edge list in the shared folder and labels come back the same way, so no row passes
through the driver. The library keeps its graph in executor storage (spilling to disk) and its lineage grows with
its rounds: a lost executor may cost it all of them. It is here to be compared with, not to be built on.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.plans.metrics import Run
from graphcc.session import remove, scratch_path


def available(spark) -> bool:
    """Whether the library's classes can be loaded in this session."""
    try:
        spark.sparkContext._jvm.java.lang.Class.forName("org.apache.spark.graphx.GraphLoader")
    except Exception:  # noqa: BLE001  whatever the gateway makes of a missing class
        return False
    return True


def components(edges: DataFrame, run: Run | None = None) -> DataFrame:
    """``(node, component)``; raises RuntimeError where the session has no graph library."""
    spark, run = edges.sparkSession, run or Run("graph_library")
    if not available(spark):
        raise RuntimeError("this session has no graph library on its class path")
    jvm, context = spark.sparkContext._jvm, spark.sparkContext._jsc.sc()
    source, out = scratch_path(spark, "edge-list"), scratch_path(spark, "labels")
    edges.where("u <> v").select(F.concat_ws(" ", "u", "v")).write.text(source)
    spills = jvm.org.apache.spark.storage.StorageLevel.MEMORY_AND_DISK()
    ints = getattr(getattr(jvm.scala.reflect, "ClassTag$"), "MODULE$").Int()
    with run.timed("library"):
        graph = jvm.org.apache.spark.graphx.GraphLoader.edgeListFile(context, source, False, -1, spills, spills)
        labels = jvm.org.apache.spark.graphx.lib.ConnectedComponents.run(graph, ints, ints)
        labels.vertices().saveAsTextFile(out)
    for held in (labels, graph):
        held.unpersist(False)
    remove(spark, source)
    pair = F.split(F.translate("value", "()", ""), ",")
    return spark.read.text(out).select(pair[0].cast("long").alias("node"), pair[1].cast("long").alias("component"))
