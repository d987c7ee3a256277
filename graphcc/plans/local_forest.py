"""Phase 1: every partition reduces its own edges to a forest, without a shuffle.

The vector kernel hooks larger roots under smaller ones and jumps pointers in numpy; its
result does not depend on the order of edges, so a retried task repeats it. The weighted
kernel is the sequential structure, edge by edge. Memory is bounded: a task reduces its edges to a
star from time to time, and one that holds ``max_local_nodes`` starts a new forest, the same as a finer split. With None a
partition is one forest whatever its size, in memory that grows with its nodes.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphcc.baselines.sequential import DisjointSets

PAIRS = "child long, parent long"
MAX_LOCAL_NODES = 2_000_000
#: Edges held before they are reduced to their star, at least: arrays of 16 MB each.
REDUCE_ROWS = 1 << 20


def local_roots(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct ids, and for each the smallest id of its local component."""
    ids, where = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = where[: len(u)], where[len(u) :]
    parent = np.arange(len(ids))
    while True:
        ra, rb = parent[a], parent[b]
        apart = ra != rb
        if not apart.any():
            return ids, ids[parent]
        a, b = ra[apart], rb[apart]
        np.minimum.at(parent, np.maximum(a, b), np.minimum(a, b))
        while True:
            up = parent[parent]
            if np.array_equal(up, parent):
                break
            parent = up


def _star(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    ids, root = local_roots(u, v)
    child = ids != root
    tops = np.unique(root[child])
    return np.concatenate([ids[child], tops]), np.concatenate([root[child], tops])


def _weighted(u: np.ndarray, v: np.ndarray, emit: str) -> tuple[np.ndarray, np.ndarray]:
    sets, pairs, won = DisjointSets(), [], {}
    for a, b in zip(u.tolist(), v.tolist(), strict=True):
        if linked := sets.union(a, b):
            pairs.append(linked)
            won[linked[1]] = True
    if emit == "star":
        pairs = [(x, r) for x in list(sets.parent) if (r := sets.find(x)) != x]
        won = dict.fromkeys(r for _, r in pairs)
    pairs += [(r, r) for r in won]
    both = np.array(pairs, np.int64).reshape(-1, 2)
    return both[:, 0], both[:, 1]


def _kernel(emit: str, kernel: str, most: int | None, tagged: bool):
    most = sys.maxsize if most is None else most

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get().partitionId()
        held: list[tuple[np.ndarray, np.ndarray]] = []
        rows, last, reducible = 0, 0, kernel == "vector" and emit == "star"  # last: rows of the star among what is held

        def flush() -> Iterator[pa.RecordBatch]:
            u, v = (np.concatenate(x) for x in zip(*held, strict=True))
            child, parent = _star(u, v) if kernel == "vector" and emit == "star" else _weighted(u, v, emit)
            for at in range(0, len(child), 1 << 20):
                cols = [pa.array(child[at : at + (1 << 20)]), pa.array(parent[at : at + (1 << 20)])]
                if tagged:
                    cols.append(pa.array(np.full(len(cols[0]), task, np.int32)))
                yield pa.RecordBatch.from_arrays(cols, ["child", "parent", *["task"] * tagged])

        for batch in batches:
            u, v = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            if len(u):
                held.append((u, v))
                rows += len(u)
            if reducible and rows >= max(min(REDUCE_ROWS, 2 * most), 2 * last):
                # Reduce what is held to its star first; flush only if that stays large.
                held = [_star(*(np.concatenate(x) for x in zip(*held, strict=True)))]
                last = rows = len(held[0][0])
            if rows >= (most if reducible else 2 * most):
                yield from flush()
                held, rows, last = [], 0, 0
        if held:
            yield from flush()

    return run


def place(edges: DataFrame, partitioning: str = "input", k: int | None = None) -> DataFrame:
    """Deal edges to partitions: as read, round robin, by hash of u, or by range of u."""
    if partitioning == "input":
        return edges.coalesce(k) if k else edges
    n = k or edges.sparkSession.sparkContext.defaultParallelism
    if partitioning == "round_robin":
        return edges.repartition(n)
    if partitioning == "hash":
        return edges.repartition(n, "u")
    if partitioning == "range":
        return edges.repartitionByRange(n, "u")
    raise ValueError(f"unknown partitioning {partitioning!r}")


def local_forest(
    edges: DataFrame, k: int | None = None, partitioning: str = "input", emit: str = "star", kernel: str = "vector", max_local_nodes: int | None = MAX_LOCAL_NODES, tagged: bool = False
) -> DataFrame:
    """Parent pairs and self-links ``(child, parent)`` of each partition's forest; ``tagged`` adds the task's number."""
    if emit not in ("star", "incremental") or kernel not in ("vector", "weighted"):
        raise ValueError("emit is star or incremental, kernel is vector or weighted")
    return place(edges, partitioning, k).select("u", "v").mapInArrow(_kernel(emit, kernel, max_local_nodes, tagged), PAIRS + ", task int" * tagged)


def second_level(pairs: DataFrame, factor: int = 8, max_local_nodes: int | None = MAX_LOCAL_NODES) -> DataFrame:
    """The local step once more over groups of ``factor`` neighbouring partitions, still without a shuffle."""
    n = max(1, pairs.rdd.getNumPartitions() // factor)
    return pairs.select(F.col("child").alias("u"), F.col("parent").alias("v")).coalesce(n).mapInArrow(_kernel("star", "vector", max_local_nodes, False), PAIRS)
