"""What a run measures: one row per phase, round and metric, gathered by observations on the way."""

from __future__ import annotations

import time
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

SCHEMA = "run string, phase string, round int, metric string, value double"


@dataclass
class Run:
    """Collects measures of one run; ``rounds`` and ``converged`` summarise it."""

    name: str = "run"
    rows: list[tuple] = field(default_factory=list)
    converged: bool = True

    def add(self, phase: str, round_: int, **values: float) -> None:
        self.rows += [(self.name, phase, round_, k, float(v or 0)) for k, v in values.items()]

    @contextmanager
    def timed(self, phase: str, round_: int = 0):
        began = time.perf_counter()
        yield
        self.add(phase, round_, seconds=time.perf_counter() - began)

    def value(self, phase: str, metric: str, round_: int | None = None) -> float:
        return sum(r[4] for r in self.rows if r[1] == phase and r[3] == metric and round_ in (None, r[2]))

    def rounds(self, phase: str = "elect") -> int:
        return max([0, *(r[2] for r in self.rows if r[1] == phase)])

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, SCHEMA)


def observed(df: DataFrame, fingerprint: list[str] | None = None, **sums) -> tuple[DataFrame, Observation]:
    """``df`` that reports its row count and the given sums when it is next computed.

    ``fingerprint`` adds the exclusive or of the rows' hashes over these columns: it cannot overflow, however many rows.
    """
    seen = Observation()
    each = [F.coalesce(F.sum(c.cast("long")), F.lit(0)).alias(k) for k, c in sums.items()]
    if fingerprint:
        each.append(F.coalesce(F.bit_xor(F.xxhash64(*fingerprint)), F.lit(0)).alias("fingerprint"))
    return df.observe(seen, F.count(F.lit(1)).alias("n"), *each), seen


def local_reduction(run: Run) -> dict[str, float]:
    """1 - emitted / (2 N), counting pairs alone and pairs with self-links."""
    n, pairs, loops = run.value("input", "edges"), run.value("local", "pairs"), run.value("local", "self_links")
    return {"pairs": 1 - pairs / (2 * n), "with_self_links": 1 - (pairs + loops) / (2 * n)} if n else {"pairs": 0.0, "with_self_links": 0.0}


def prune_rates(run: Run) -> dict[int, float]:
    """By round: the share of children that met a single foreign parent and left for good."""
    rounds = range(1, run.rounds() + 1)
    return {r: run.value("elect", "resolved", r) / n for r in rounds if (n := run.value("elect", "groups", r))}


def speedups(edges: int, seconds: dict[str, float], ours: str) -> list[tuple[str, float, float, float]]:
    """``(method, seconds, how many times ours is faster, edges a second)`` of one input."""
    return [(name, s, s / seconds[ours], edges / s) for name, s in seconds.items()]


def doubling_efficiency(sizes: list[tuple[int, float]]) -> list[float]:
    """Growth of edges over growth of seconds, from each size to the next: 1 is linear, more is better."""
    return [(b / a) / (t / s) for (a, s), (b, t) in zip(sizes, sizes[1:], strict=False)]


def compute_cost(executors: int, memory_gb: float, seconds: float) -> float:
    """GB-hours of executor memory held."""
    return executors * memory_gb * seconds / 3600


def partition_profile(df: DataFrame, key: str | None = None) -> DataFrame:
    """Rows of the fullest and the mean partition, and of the largest group of ``key``."""
    per = df.groupBy(F.spark_partition_id().alias("p")).count()
    out = per.agg(F.count("p").alias("partitions"), F.max("count").alias("most"), F.avg("count").alias("mean"))
    if key:
        out = out.crossJoin(df.groupBy(key).count().agg(F.max("count").alias("largest_group")))  # one row each
    return out
