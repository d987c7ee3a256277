"""A Python data source of graphs with known shape: chain, star, cliques, random."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.shape, self.n = options.get("shape", "chain"), int(options.get("n", "100"))
        self.size, self.seed, self.parts = int(options.get("clique", "20")), int(options.get("seed", "7")), int(options.get("partitions", "4"))

    def partitions(self) -> list[InputPartition]:
        cuts = np.linspace(0, self.n, self.parts + 1).astype(int)
        return [_Range(int(a), int(b)) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]

    def read(self, partition: _Range) -> Iterator[pa.RecordBatch]:
        """Edge i of ``n`` (cliques: all edges of node i to larger nodes of its clique)."""
        i = np.arange(partition.first, partition.last, dtype=np.int64)
        if self.shape == "chain":
            u, v = i, i + 1
        elif self.shape == "star":
            u, v = np.zeros_like(i), i + 1
        elif self.shape == "cliques":
            ends = np.minimum((i // self.size + 1) * self.size, self.n)
            u = np.repeat(i, ends - i - 1)
            v = u + 1 + np.concatenate([np.arange(x) for x in (ends - i - 1).tolist()] or [np.zeros(0, np.int64)]).astype(np.int64)
        elif self.shape == "random":
            rng = np.random.default_rng([self.seed, partition.first])
            u, v = (rng.integers(0, max(2, self.n // 3), len(i), dtype=np.int64) for _ in range(2))
        else:
            raise ValueError(f"unknown shape {self.shape!r}")
        yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["u", "v"])


class SyntheticGraph(DataSource):
    """``spark.read.format('synthetic_graph').option('shape', 'chain').option('n', 100).load()``"""

    @classmethod
    def name(cls) -> str:
        return "synthetic_graph"

    def schema(self) -> str:
        return "u bigint, v bigint"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SyntheticGraph)
