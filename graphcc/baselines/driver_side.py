"""Sequential union-find as a method of the common interface: one task over all edges, whatever their number."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from graphcc.baselines.sequential import DenseSets
from graphcc.session import keep

#: Edges read back, and rows given out, at once.
CHUNK_ROWS = 1 << 18


def _least_of_trees(parent: np.ndarray) -> np.ndarray:
    """For each node the smallest node of its tree."""
    while not np.array_equal(up := parent[parent], parent):
        parent = up
    least = np.empty(len(parent), np.int64)
    least[parent[::-1]] = np.arange(len(parent) - 1, -1, -1)  # of equal places the last assignment stays
    return least[parent]


def sequential_components(edges: DataFrame, weighted: bool = True, compress: bool = True) -> DataFrame:
    """All edges through one union-find, in the order they come in.

    The task writes the edges to a file of its own, 16 bytes each, while it collects the distinct ends; a node is then known by
    its place among the sorted ends. So memory is some tens of bytes a node, and grows with no number of edges.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, new, waiting = np.zeros(0, np.int64), [], 0
        with tempfile.TemporaryFile() as held:
            for b in batches:
                both = np.stack([b.column(i).to_numpy(zero_copy_only=False) for i in (0, 1)], axis=1)
                both = np.ascontiguousarray(both[both[:, 0] != both[:, 1]])
                held.write(both)
                new.append(np.unique(both))
                waiting += len(new[-1])
                if waiting >= max(CHUNK_ROWS, len(ids)):
                    ids, new, waiting = np.unique(np.concatenate([ids, *new])), [], 0
            ids, new = np.unique(np.concatenate([ids, *new])), []
            sets = DenseSets(len(ids), weighted, compress)
            held.seek(0)
            while part := held.read(16 * CHUNK_ROWS):
                places = np.searchsorted(ids, np.frombuffer(part, np.int64))
                for u, v in zip(places[::2].tolist(), places[1::2].tolist(), strict=True):
                    sets.union(u, v)
        least = _least_of_trees(np.frombuffer(sets.parent, np.int64))
        for at in range(0, len(ids), CHUNK_ROWS):
            some = slice(at, at + CHUNK_ROWS)
            yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(ids[least[some]])], ["node", "component"])

    # Kept first: what makes the edges runs in parallel, and only the union-find in one task. Kept after: it runs once.
    return keep(keep(edges.select("u", "v"), "edges").coalesce(1).mapInArrow(run, "node long, component long"), "sequential")
