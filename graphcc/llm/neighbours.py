"""Approximate nearest neighbours by a hierarchical k-means tree, best bins first.

The tree is fitted on a bounded sample of the vectors (``sample_rows``, chosen by hash; more for a larger
table, up to ``MOST_SAMPLE``), as deep as the sample fills it, and every row is then put into a leaf. A query
walks the tree through a priority queue, always opening the node whose centre is nearest, and so meets the
leaves in a best-bin-first order. How many leaves are visited is calibrated: for ``calibration_rows`` queries the
true neighbours are found by brute force over all rows, in blocks, and visits are widened until the wanted
share of these neighbours lies in visited leaves; every query goes on until its leaves hold k rows besides its own.

Neighbouring leaves make a cell of about ``group_rows`` rows (a 64th of the table, between 256 and 65,536); a leaf with more is a cell in several blocks. A row
moves once, to its cell and block; queries are copied to the cells that they visit. Only where very many queries meet
one block is it copied, to split them. Of equal vectors in a batch of the scan, just those with the smallest ids are
kept as candidates, as the others cannot be among the k nearest: so a group of copies as large as a third of the
table costs its queries, not its square.

Vectors that are null, zero, or hold null or non-finite components take no part, nor do rows with a null id; rows
that share the query's id count as its own. Vectors meet those of their own length only, each length having
a tree of its own. Ties go to the smaller id. Without queries or candidates the result is empty.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from functools import reduce
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphcc.session import Kept

SCHEMA = "query_id long, rank int, vec_id long, score double"
_INDEX = "vec_id long, embedding array<float>, leaf int, candidate boolean"
#: Sampled vectors at most, however large the table; a leaf is fitted on this many of them at least, so there are at most 10,922 leaves.
MOST_SAMPLE, LEAF_SAMPLE = 262_144, 24


def matrix(batch: pa.RecordBatch, dims: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and float32 vectors of the valid rows."""
    col = batch.column("embedding").cast(pa.large_list(pa.float32()))
    ok = pc.and_(pc.fill_null(pc.equal(pc.list_value_length(col), dims), False), batch.column("vec_id").is_valid())
    batch_ids, col = batch.column("vec_id").filter(ok), col.filter(ok)
    x = pc.fill_null(col.flatten(), np.nan).to_numpy(zero_copy_only=False).reshape(-1, dims)
    good = np.isfinite(x).all(axis=1) & (x != 0).any(axis=1)
    return batch_ids.to_numpy(zero_copy_only=False).astype(np.int64)[good], np.ascontiguousarray(x[good])


def unit(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.float64)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def kmeans(x: np.ndarray, k: int, rng: np.random.Generator, turns: int = 8) -> np.ndarray:
    """Unit centres of unit vectors; fewer than ``k`` if clusters run empty."""
    centres = x[rng.choice(len(x), k, replace=False)]
    for _ in range(turns):
        near = (x @ centres.T).argmax(axis=1)
        sums = np.zeros_like(centres)
        np.add.at(sums, near, x)
        size = np.sqrt((sums * sums).sum(axis=1))
        centres = sums[size > 1e-9] / size[size > 1e-9, None]
    return centres


@dataclass
class Tree:
    """Centres of all nodes, children of inner ones, leaf numbers of the others; node 0 is the root."""

    centres: list = field(default_factory=list)
    children: list = field(default_factory=list)
    leaf: list = field(default_factory=list)
    leaves: int = 0

    @classmethod
    def fit(cls, x: np.ndarray, branching: int = 16, depth: int = 8, leaf_rows: int = LEAF_SAMPLE, seed: int = 5) -> Tree:
        tree, rng = cls(), np.random.default_rng(seed)
        x = unit(x)

        def grow(rows: np.ndarray, centre: np.ndarray, level: int) -> int:
            me = len(tree.centres)
            tree.centres.append(centre)
            tree.children.append([])
            tree.leaf.append(-1)
            k = min(branching, len(rows) // leaf_rows)
            if level < depth and k > 1:
                centres = kmeans(x[rows], k, rng)
                near = (x[rows] @ centres.T).argmax(axis=1)
                for c in range(len(centres)):
                    tree.children[me].append(grow(rows[near == c], centres[c], level + 1))
            if not tree.children[me]:
                tree.leaf[me], tree.leaves = tree.leaves, tree.leaves + 1
            return me

        grow(np.arange(len(x)), np.zeros(x.shape[1]), 0)
        tree.centres = np.array(tree.centres)
        return tree

    def assign(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each vector: at every level the nearest centre."""
        x, out = unit(x), np.zeros(len(x), np.int64)

        def down(node: int, rows: np.ndarray) -> None:
            kids = self.children[node]
            if not kids or not len(rows):
                out[rows] = self.leaf[node]
                return
            best = (x[rows] @ self.centres[kids].T).argmax(axis=1)
            for i, kid in enumerate(kids):
                down(kid, rows[best == i])

        down(0, np.arange(len(x)))
        return out

    def visit(self, x: np.ndarray, most: int, rows: np.ndarray | None = None, least: int = 0) -> Iterator[list[int]]:
        """For each vector the first ``most`` leaves, best bin first, and further ones until they hold ``least`` rows, ``rows`` being each leaf's."""
        for v in unit(x):
            queue, met, held = [(0.0, 0)], [], 0
            while queue and (len(met) < most or held < least):
                _, node = heapq.heappop(queue)
                if kids := self.children[node]:
                    for near, kid in zip((self.centres[kids] @ v).tolist(), kids, strict=True):
                        heapq.heappush(queue, (-near, kid))
                else:
                    met.append(self.leaf[node])
                    held += 0 if rows is None else int(rows[self.leaf[node]])
            yield met


def exact(q: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Cosines of one vector with rows, in double precision; equal rows give equal values."""
    q, rows = q.astype(np.float64), rows.astype(np.float64)
    return (rows * q).sum(axis=1) / (np.sqrt((rows * rows).sum(axis=1)) * np.sqrt((q * q).sum()))


def best_of(qid: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, k: int, allowed=None):
    """Query position, row position and score of each query's ``k`` nearest rows; ``allowed(a, b)``: query by row, of queries a to b."""
    out: list[tuple[int, int, float]] = []
    ux, block = unit(x), max(1, min(256, (1 << 21) // max(1, len(x))))
    for a in range(0, len(q), block):
        near = unit(q[a : a + block]) @ ux.T
        near[qid[a : a + block, None] == ids[None, :]] = -9
        if allowed is not None:
            near[~allowed(a, min(a + block, len(q)))] = -9
        cut = np.partition(near, -k, axis=1)[:, -k] if near.shape[1] > k else np.full(len(near), -9.0)
        for i, (row, low) in enumerate(zip(near, cut, strict=True)):
            c = np.flatnonzero((row >= low - 1e-9) & (row > -8))  # all that may tie with the last
            if len(c):
                score = exact(q[a + i], x[c])
                for j in np.lexsort((ids[c], -score))[:k]:
                    out.append((a + i, int(c[j]), float(score[j])))
    return out


def _rows(found, qid, ids, extra=None) -> pa.RecordBatch:
    cols = [pa.array([int(qid[i]) for i, _, _ in found], pa.int64()), pa.array([int(ids[j]) for _, j, _ in found], pa.int64()), pa.array([s for _, _, s in found], pa.float64())]
    names = ["query_id", "vec_id", "score"]
    if extra is not None:
        cols.append(pa.array([int(extra[j]) for _, j, _ in found], pa.int32()))
        names.append("leaf")
    return pa.RecordBatch.from_arrays(cols, names)


def _smallest_of_equals(ids: np.ndarray, x: np.ndarray, most: int) -> np.ndarray:
    """Which rows are among the ``most`` with the smallest ids of those with the same vector."""
    _, same = np.unique(x.view(np.dtype((np.void, x.itemsize * x.shape[1]))).ravel(), return_inverse=True)
    order = np.lexsort((ids, same))
    starts = np.concatenate(([True], same[order][1:] != same[order][:-1]))
    place = np.arange(len(ids)) - np.maximum.accumulate(np.where(starts, np.arange(len(ids)), 0))
    out = np.empty(len(ids), bool)
    out[order] = place < most
    return out


def _assign(shared, dims: int, most: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = shared.value
        for batch in batches:
            for a in range(0, batch.num_rows, 4096):
                ids, x = matrix(batch.slice(a, 4096), dims)
                if len(ids):
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1, dtype=np.int32) * dims), pa.array(x.ravel()))
                    cols = [pa.array(ids), lists, pa.array(tree.assign(x).astype(np.int32)), pa.array(_smallest_of_equals(ids, x, most))]
                    yield pa.RecordBatch.from_arrays(cols, ["vec_id", "embedding", "leaf", "candidate"])

    return run


def _brute(shared, dims: int, k: int):
    """Top ``k`` of each broadcast query among the rows of a task, with their leaves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, q = shared.value
        for batch in batches:
            for a in range(0, batch.num_rows, 4096):
                part = batch.slice(a, 4096)
                ids, x = matrix(part, dims)
                if len(ids):
                    yield _rows(best_of(qid, q, ids, x, k), qid, ids, part.column("leaf").to_numpy())

    return run


def cells_of(held: np.ndarray, group_rows: int) -> tuple[np.ndarray, np.ndarray]:
    """The cell of each leaf, and the blocks of each cell: neighbouring leaves together up to ``group_rows`` rows."""
    cell, blocks, inside = np.zeros(len(held), np.int64), [], 0
    for leaf, n in enumerate(held.tolist()):
        if not blocks or inside + n > group_rows:
            blocks.append(1)
            inside = 0
        inside += n
        blocks[-1] = max(1, -(-inside // group_rows))
        cell[leaf] = len(blocks) - 1
    return cell, np.array(blocks, np.int64)


def _routes(shared, dims: int, visits: int, held: np.ndarray, least: int, cell: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = shared.value
        for batch in batches:
            for a in range(0, batch.num_rows, 4096):
                ids, x = matrix(batch.slice(a, 4096), dims)
                row, cells, leaves = [], [], []
                for i, met in enumerate(tree.visit(x, visits, held, least)):
                    by: dict[int, list[int]] = {}
                    for leaf in met:
                        by.setdefault(int(cell[leaf]), []).append(leaf)
                    row += [i] * len(by)
                    cells += by.keys()
                    leaves += by.values()
                if row:
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(row) + 1, dtype=np.int32) * dims), pa.array(x[row].ravel()))
                    yield pa.RecordBatch.from_arrays([pa.array(ids[row]), lists, pa.array(cells, pa.int32()), pa.array(leaves, pa.list_(pa.int32()))], ["vec_id", "embedding", "cell", "leaves"])

    return run


def _meet(dims: int, k: int):
    def run(queries: pa.Table, rows: pa.Table) -> pa.Table:
        empty = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())]).empty_table()
        if not queries.num_rows or not rows.num_rows:
            return empty
        q, r = queries.combine_chunks().to_batches()[0], rows.combine_chunks().to_batches()[0]
        qid, qx = matrix(q, dims)
        ids, x = matrix(r, dims)
        leaf, lists = r.column("leaf").to_numpy(), q.column("leaves").to_pylist()
        low = int(leaf.min())
        width = int(leaf.max()) - low + 1

        def wanted(a: int, b: int) -> np.ndarray:
            out = np.zeros((b - a, width), bool)
            for i, ls in enumerate(lists[a:b]):
                out[i, [n - low for n in ls if 0 <= n - low < width]] = True
            return out[:, leaf - low]

        return pa.Table.from_batches([_rows(best_of(qid, qx, ids, x, k, wanted), qid, ids)])

    return run


def top_k(scored: DataFrame, k: int) -> DataFrame:
    by = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return scored.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k)


def _sampled(df: DataFrame, total: int, rows: int, salt: int) -> DataFrame:
    """About ``rows`` of the rows, by hash of the id: the same ones in every run."""
    top = min(2**63 - 1, int((2 * min(1.0, rows / max(1, total)) - 1) * 2**63))
    return df.where(F.xxhash64("vec_id", F.lit(salt)) <= top)


def _matrix_of(df: DataFrame, dims: int) -> tuple[np.ndarray, np.ndarray]:
    table = df.select("vec_id", "embedding").orderBy("vec_id").toArrow().combine_chunks()
    return matrix(table.to_batches()[0], dims) if table.num_rows else (np.zeros(0, np.int64), np.zeros((0, dims), np.float32))


def nearest(
    vectors: DataFrame, is_query, k: int = 5, recall: float = 0.97, sample_rows: int = 16_000, calibration_rows: int = 200, branching: int = 16, group_rows: int | None = None, group_queries: int = 16_384
) -> DataFrame:
    """``(query_id, rank, vec_id, score)`` of the rows of ``vectors(vec_id, embedding)`` for which ``is_query`` holds."""
    spark, vectors = vectors.sparkSession, vectors.select("vec_id", "embedding").where("vec_id IS NOT NULL AND size(embedding) > 0")
    lengths = vectors.groupBy(F.size("embedding").alias("d")).agg(F.count(F.lit(1)).alias("n")).orderBy("d").collect()  # one row a length
    options = {"k": k, "recall": recall, "sample_rows": sample_rows, "calibration_rows": calibration_rows, "branching": branching, "group_rows": group_rows, "group_queries": group_queries}
    parts = [_nearest_of(vectors.where(F.size("embedding") == r.d), is_query, r.d, r.n, **options) for r in lengths]
    return reduce(DataFrame.unionByName, parts) if parts else spark.createDataFrame([], SCHEMA)


def _fitted(vectors: DataFrame, dims: int, total: int, sample_rows: int, branching: int) -> Tree | None:
    wanted = min(MOST_SAMPLE, max(sample_rows, total // 64))
    _, sample = _matrix_of(_sampled(vectors, total, wanted, 1), dims)
    if not len(sample):
        _, sample = _matrix_of(vectors.limit(1000), dims)
    return Tree.fit(sample, branching) if len(sample) else None


def _calibrated(index: DataFrame, shared, tree: Tree, dims: int, total: int, rows: int, k: int, recall: float) -> int:
    """Leaves to visit, so that the wanted share of the true neighbours of sampled queries lies in them."""
    qid, q = _matrix_of(_sampled(index, total, rows, 2), dims)
    qid, first = np.unique(qid, return_index=True)
    if not len(qid):
        return tree.leaves
    asked = index.sparkSession.sparkContext.broadcast((qid, q[first]))
    met = index.where("candidate").mapInArrow(_brute(asked, dims, k), "query_id long, vec_id long, score double, leaf int")
    truth = top_k(met, k).select("query_id", "leaf").collect()
    order = {int(i): {leaf: n + 1 for n, leaf in enumerate(ls)} for i, ls in zip(qid, tree.visit(q[first], tree.leaves), strict=True)}
    visits = sorted(order[r.query_id][r.leaf] for r in truth)
    return min(tree.leaves, visits[min(len(visits) - 1, int(np.ceil(recall * len(visits))))]) if visits else tree.leaves


def _nearest_of(vectors: DataFrame, is_query, dims: int, total: int, k: int, recall: float, sample_rows: int, calibration_rows: int, branching: int, group_rows: int | None, group_queries: int) -> DataFrame:
    """The neighbours among vectors of ``dims`` components."""
    spark = vectors.sparkSession
    tree = _fitted(vectors, dims, total, sample_rows, branching)
    if tree is None:
        return spark.createDataFrame([], SCHEMA)
    # A query's leaves must hold k rows besides those of its own id, and so many of equal vectors are kept.
    least = k + (vectors.groupBy("vec_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("n")).first().n or 0)
    shared = spark.sparkContext.broadcast(tree)
    index = Kept(vectors.mapInArrow(_assign(shared, dims, least), _INDEX), "index").df
    visits = _calibrated(index, shared, tree, dims, total, calibration_rows, k, recall)

    held = np.zeros(tree.leaves, np.int64)
    for r in index.where("candidate").groupBy("leaf").agg(F.count(F.lit(1)).alias("n")).collect():
        held[r.leaf] = r.n
    cell, blocks = cells_of(held, group_rows or min(1 << 16, max(1 << 8, total >> 6)))
    asking = index.where(is_query).select("vec_id", "embedding").mapInArrow(_routes(shared, dims, visits, held, least, cell), "vec_id long, embedding array<float>, cell int, leaves array<int>")
    routes = Kept(asking, "routes").df
    met = {r.cell: r.n for r in routes.groupBy("cell").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not met:
        return spark.createDataFrame([], SCHEMA)
    split = spark.createDataFrame([(c, int(blocks[c]), -(-n // group_queries)) for c, n in met.items()], "cell int, row_blocks int, query_blocks int")
    of_leaf = spark.createDataFrame([(leaf, int(c)) for leaf, c in enumerate(cell) if int(c) in met], "leaf int, cell int").join(split, "cell")
    # Both tables have a row a leaf at most, and so are as bounded as the tree is.
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    left = routes.join(F.broadcast(split), "cell").withColumn("qb", F.pmod(F.xxhash64("vec_id"), F.col("query_blocks")).cast("int")).withColumn("rb", every("row_blocks"))
    right = index.where("candidate").join(F.broadcast(of_leaf), "leaf").withColumn("rb", F.pmod(F.xxhash64("vec_id", F.lit(3)), F.col("row_blocks")).cast("int")).withColumn("qb", every("query_blocks"))
    keys = ["cell", "qb", "rb"]
    left, right = left.select(*keys, "vec_id", "embedding", "leaves"), right.select(*keys, "vec_id", "embedding", "leaf")
    scored = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(_meet(dims, k), "query_id long, vec_id long, score double")
    return top_k(scored, k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
