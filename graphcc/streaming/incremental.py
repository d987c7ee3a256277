"""Components of a growing edge set, batch by batch.

State lives in two tables in shared storage. ``nodes`` is append-only: every node with the root it had when it
first came, one folder a batch. ``roots`` maps these roots to the current components and is written anew,
as a version, by each batch: it holds roots only, so merging two components of a billion nodes rewrites
two rows. Node folders are folded into one, sorted by node, every ``FOLD_EVERY`` batches; a batch finds its own
nodes by reading the row groups that meet the ranges its ids lie in, ``BANDS`` of them at most. It works on the
contracted graph of its edges' ends, then commits by its version's success mark; run again, it overwrites its own
folders. Union is commutative and monotone, so late edges need no retraction.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from graphcc.plans.components import connected_components
from graphcc.schema import check_edges
from graphcc.session import Kept, exists, remove, scratch_path


#: Batches after which their folders of nodes become one, so that a batch reads few folders however many came before.
FOLD_EVERY = 16
#: Ranges of ids, of equal width, that a batch's nodes are looked up by.
BANDS = 64


def within_bands(nodes: DataFrame, ends: DataFrame) -> DataFrame:
    """Rows of ``nodes`` that may be among ``ends``: the scan skips row groups outside the ranges where these lie."""
    span = ends.agg(F.min("node").alias("low"), F.max("node").alias("high")).first()
    if span.low is None:
        return nodes.limit(0)
    width = max(1.0, (float(span.high) - float(span.low)) / BANDS)  # in doubles: the ids may span all 64 bits
    band = F.floor((F.col("node").cast("double") - F.lit(float(span.low))) / F.lit(width))
    met = ends.groupBy(band.alias("band")).agg(F.min("node").alias("low"), F.max("node").alias("high")).collect()  # a row a band
    return nodes.where(reduce(lambda a, b: a | b, [F.col("node").between(r.low, r.high) for r in met]))


class ComponentState:
    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def _names(self, kind: str) -> list[str]:
        jvm = self.spark.sparkContext._jvm
        top = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{kind}")
        fs = top.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        return [s.getPath().getName() for s in fs.listStatus(top)] if fs.exists(top) else []

    def _versions(self) -> list[int]:
        return sorted(int(n) for n in self._names("roots") if exists(self.spark, f"{self.path}/roots/{n}/_SUCCESS"))

    def _node_folders(self, last: int) -> list[str]:
        """Folders that hold the nodes of batches up to ``last``: the newest folded one, and those of later batches."""
        names = self._names("nodes")
        folded = [int(n[5:]) for n in names if n.startswith("upto-") and int(n[5:]) <= last and exists(self.spark, f"{self.path}/nodes/{n}/_SUCCESS")]
        base = max(folded, default=-1)
        return ([f"upto-{base}"] if folded else []) + [n for n in names if n.isdigit() and base < int(n) <= last]

    def fold(self, last: int) -> None:
        """Bring the nodes of batches up to ``last`` into one folder, sorted by node, then drop what it replaces."""
        names = self._node_folders(last)
        if len(names) < 2:
            return
        nodes = self.spark.read.schema("node long, root long").parquet(*[f"{self.path}/nodes/{n}" for n in names])
        nodes.repartitionByRange("node").sortWithinPartitions("node").write.mode("overwrite").parquet(f"{self.path}/nodes/upto-{last}")
        for n in names:
            remove(self.spark, f"{self.path}/nodes/{n}")

    def _read(self, below: int | None = None) -> tuple[DataFrame, DataFrame]:
        """``nodes(node, root)`` and ``roots(root, component)`` as of the last committed batch before ``below``."""
        done = [v for v in self._versions() if below is None or v < below]
        nodes = self.spark.createDataFrame([], "node long, root long")
        if not done:
            return nodes, self.spark.createDataFrame([], "root long, component long")
        made = [f"{self.path}/nodes/{name}" for name in self._node_folders(done[-1])]
        nodes = self.spark.read.schema("node long, root long").parquet(*made) if made else nodes
        return nodes, self.spark.read.schema("root long, component long").parquet(f"{self.path}/roots/{done[-1]}")

    def components(self) -> DataFrame:
        """``(node, component)`` now."""
        nodes, roots = self._read()
        return nodes.join(roots, "root").select("node", "component")

    def apply(self, batch: DataFrame, batch_id: int, **options) -> None:
        """Fold one batch of edges into the state; a batch applied again changes nothing."""
        nodes, roots = self._read(batch_id)
        edges = Kept(check_edges(batch).where("u <> v").distinct(), "batch")
        both = edges.df.select(F.explode(F.array("u", "v")).alias("node"))
        known = both.distinct().join(within_bands(nodes, both), "node", "left").join(roots, "root", "left")
        here = Kept(known.select("node", F.coalesce("component", "node").alias("at"), F.col("root").isNull().alias("fresh")), "ends")
        one, two = here.df.select(F.col("node").alias("u"), F.col("at").alias("x")), here.df.select(F.col("node").alias("v"), F.col("at").alias("y"))
        contracted = edges.df.join(one, "u").join(two, "v").where("x <> y").select(F.col("x").alias("u"), F.col("y").alias("v")).distinct()
        moved = Kept(connected_components(contracted, **options).select(F.col("node").alias("old"), F.col("component").alias("new")), "moved")
        at_last = here.df.where("fresh").join(moved.df, F.col("at") == F.col("old"), "left").select("node", F.coalesce("new", "at").alias("root"))
        at_last.write.mode("overwrite").parquet(f"{self.path}/nodes/{batch_id}")
        fresh = self.spark.read.schema("node long, root long").parquet(f"{self.path}/nodes/{batch_id}").select("root", F.col("root").alias("component")).distinct()
        renamed = roots.join(moved.df, F.col("component") == F.col("old"), "left").select("root", F.coalesce("new", "component").alias("component"))
        every = renamed.union(fresh.join(renamed.select("root"), "root", "left_anti"))
        every.write.mode("overwrite").parquet(f"{self.path}/roots/{batch_id}")
        for t in (edges, here, moved):
            t.drop()
        for v in self._versions():
            if v < batch_id - 1:  # the last two versions stay: one may be needed to repeat a batch
                remove(self.spark, f"{self.path}/roots/{v}")
        if batch_id % FOLD_EVERY == FOLD_EVERY - 1:
            self.fold(batch_id - 1)  # the last batch may have to be repeated


def incremental_components(edge_stream: DataFrame, state_path: str, checkpoint: str | None = None, **options) -> StreamingQuery:
    """Start a query that keeps components of a stream of edges; stops when what is there has been read."""
    spark = edge_stream.sparkSession
    state = ComponentState(spark, state_path)
    return (
        edge_stream.writeStream.foreachBatch(lambda df, i: state.apply(df, i, **options))
        .option("checkpointLocation", checkpoint or scratch_path(spark, "stream")).trigger(availableNow=True).start()
    )
