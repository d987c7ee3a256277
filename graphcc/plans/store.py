"""Rounds kept as Parquet in the shared folder: one write a round, finished and live rows apart by partition.

A round counts once its success mark is there, so a restarted driver continues after the
last finished round; live rows of a round are dropped when the next one is complete.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphcc.session import exists, remove, scratch_path

_PAIR = "child long, parent long"


class RoundStore:
    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path = spark, path or scratch_path(spark, "rounds")
        self.rounds: list[int] = []
        r = 1
        while exists(spark, f"{self.path}/round={r}/_SUCCESS"):
            self.rounds.append(r)
            r += 1

    def write(self, r: int, judged: DataFrame) -> None:
        """Commit round ``r`` of ``(kind, child, parent)``."""
        judged.write.mode("overwrite").partitionBy("kind").parquet(f"{self.path}/round={r}")
        self.rounds.append(r)
        remove(self.spark, f"{self.path}/round={r - 1}/kind=live")

    def seed(self, live: DataFrame) -> DataFrame:
        """Materialise what the rounds start from."""
        live.write.mode("overwrite").parquet(f"{self.path}/seed")
        return self.spark.read.schema(_PAIR).parquet(f"{self.path}/seed")

    def live(self, r: int) -> DataFrame:
        return self._kind(r, "live") if r else self.spark.read.schema(_PAIR).parquet(f"{self.path}/seed")

    def _kind(self, r: int, kind: str) -> DataFrame:
        at = f"{self.path}/round={r}/kind={kind}"
        return self.spark.read.schema(_PAIR).parquet(at) if exists(self.spark, at) else self.spark.createDataFrame([], _PAIR)

    def forest(self) -> DataFrame:
        """``(child, parent, round)`` of all committed rounds: one row for each node that is not a root."""
        found = [r for r in self.rounds if exists(self.spark, f"{self.path}/round={r}/kind=resolved")]
        if not found:
            return self.spark.createDataFrame([], _PAIR + ", round int")
        whole = self.spark.read.option("basePath", self.path).schema(_PAIR + ", kind string, round int")
        return whole.parquet(*[f"{self.path}/round={r}/kind=resolved" for r in found]).select("child", "parent", F.col("round").cast("int"))

    def drop(self) -> None:
        remove(self.spark, self.path)
