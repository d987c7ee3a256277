"""What the engine needs from a session: a shared scratch folder and tables kept in it.

Iterations cut their lineage by writing Parquet into the folder that the cluster
names in ``spark.checkpoint.dir``; every executor can read it, so a lost executor
costs a task retry and nothing more. Only a local session without that setting
gets a temporary folder of its own.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}
_MADE: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share; raises on a cluster that names none."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if named:
        return named.rstrip("/")
    app = spark.sparkContext.applicationId
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if app not in _LOCAL:
        _LOCAL[app] = tempfile.mkdtemp(prefix="graphcc-")
        atexit.register(shutil.rmtree, _LOCAL[app], ignore_errors=True)
    return f"file://{_LOCAL[app]}"


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder, removed when the driver ends."""
    path = f"{shared_dir(spark)}/graphcc/{spark.sparkContext.applicationId}/{name}-{uuid.uuid4().hex[:12]}"
    _MADE.append((spark, path))
    return path


def remove(spark: SparkSession, path: str) -> None:
    """Delete a path through Hadoop's file system, whatever store it is in."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def exists(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where)


#: Bytes of an Arrow batch in steps that are computed at once: two workers of a task hold one each, and the JVM a third.
ARROW_BYTES = 8 << 20


@contextmanager
def computed_at_once(spark: SparkSession) -> Iterator[None]:
    """Inside, Python workers get batches of at most ``ARROW_BYTES``, and a query's shuffle files go when it has ended.

    The session's own settings hold again after it.
    """
    wanted = {"spark.sql.execution.arrow.maxBytesPerBatch": str(ARROW_BYTES), "spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}
    before = {name: spark.conf.get(name, None) for name in wanted}
    for name, value in wanted.items():
        spark.conf.set(name, value)
    try:
        yield
    finally:
        for name, value in before.items():
            spark.conf.unset(name) if value is None else spark.conf.set(name, value)


class Kept:
    """A DataFrame written to the shared folder and read back; ``drop`` removes its files."""

    def __init__(self, df: DataFrame, name: str = "table", partition_by: list[str] | None = None):
        self.spark = df.sparkSession
        self.path = scratch_path(self.spark, name)
        out = df.write.mode("overwrite")
        with computed_at_once(self.spark):
            (out.partitionBy(*partition_by) if partition_by else out).parquet(self.path)
        schema = df.schema
        self.df = self.spark.read.schema(schema).parquet(self.path)

    def drop(self) -> None:
        remove(self.spark, self.path)


def keep(df: DataFrame, name: str = "table") -> DataFrame:
    """``df`` as a table in the shared folder: computed once, lineage cut, sizes known to the planner."""
    return Kept(df, name).df


@atexit.register
def _clean() -> None:
    for spark, path in _MADE:
        try:
            remove(spark, path)
        except Exception:  # noqa: BLE001  the session may have ended first
            return
