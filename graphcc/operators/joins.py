"""Joins that Spark has no operator for, as compositions of DataFrame operations."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphcc.session import Kept

#: Rows of a block of vectors, at most about; a task holds two blocks, and TILE_ROWS rows of products with one.
BLOCK_ROWS = 8192
TILE_ROWS = 256

def range_join(left: DataFrame, right: DataFrame, lt: str, rt: str, width: int, keep: Column) -> DataFrame:
    """Rows with ``|left.lt - right.rt| <= width`` (whole numbers): an equi-join on bins of that width, then a filter."""
    cell = lambda c: F.floor(F.col(c) / F.lit(width)).cast("long")
    spread = left.withColumn("__bin", F.explode(F.array(cell(lt) - 1, cell(lt), cell(lt) + 1)))
    return spread.join(right.withColumn("__bin", cell(rt)), "__bin").where((F.abs(F.col(lt) - F.col(rt)) <= width) & keep).drop("__bin")


def asof_join(rows: DataFrame, marks: DataFrame, by: list[str], order: list[str], value: str) -> DataFrame:
    """Each row of ``rows`` with the ``value`` of the last mark strictly before it: one union, one window, no join."""
    tagged = rows.withColumn("__is", F.lit(1)).withColumn("__v", F.lit(None).cast(marks.schema[value].dataType))
    both = tagged.unionByName(marks.select(*by, *order, F.col(value).alias("__v")).withColumn("__is", F.lit(0)), allowMissingColumns=True)
    before = Window.partitionBy(*by).orderBy(*order, F.col("__is").desc()).rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn(f"last_{value}", F.last("__v", ignorenulls=True).over(before)).where("__is = 1").drop("__is", "__v")


def _cosines(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Of each row of ``x`` with that of ``y``, in double, summed in the order of the components as the SQL functions do."""
    dot, xx, yy = (np.zeros(len(x)) for _ in range(3))
    for k in range(x.shape[1]):
        a, b = x[:, k].astype(np.float64), y[:, k].astype(np.float64)
        dot, xx, yy = dot + a * b, xx + a * a, yy + b * b
    return dot / np.sqrt(xx * yy)


def _unit(x: np.ndarray) -> np.ndarray:
    d = x.astype(np.float64)
    return (d / np.sqrt((d * d).sum(axis=1, keepdims=True))).astype(np.float32)


def _near_pairs(least: float, out: str):
    def run(groups: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(groups))
        right = t["right"].to_numpy()
        ids = t["id"].to_numpy()
        vectors = t["vector"].combine_chunks()
        x = vectors.flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
        same = t["i"][0].as_py() == t["j"][0].as_py()
        (a, u), (b, v) = ((x[right == side], ids[right == side]) for side in (False, True))
        if same:
            b, v = a, u
        with np.errstate(all="ignore"):
            # Rounding of unit vectors and of their products stays far below this; what lies so near is computed in double.
            slack = max(1e-4, 4e-7 * x.shape[1])
            ua, ub = _unit(a), _unit(b)
            for at in range(0, len(a), TILE_ROWS):
                first = at if same else 0
                s = ua[at : at + TILE_ROWS] @ ub[first:].T
                p, q = np.nonzero(~(s < least - slack))  # no number (a vector of zeros): near to all, as in SQL
                sure = ~(s[p, q] < least + slack)
                p, q = p + at, q + first
                if same:
                    once = p < q
                    p, q, sure = p[once], q[once], sure[once]
                p, q, sure = (z[u[p] != v[q]] for z in (p, q, sure))
                near = np.nonzero(~sure)[0]
                sure[near] = ~(_cosines(a[p[near]], b[q[near]]) < least)
                m, n = u[p[sure]], v[q[sure]]
                for k in range(0, len(m), 1 << 18):
                    some = slice(k, k + (1 << 18))
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(m[some], n[some])), pa.array(np.maximum(m[some], n[some]))], out.split(","))

    return run


def _usable(vectors: DataFrame, id_: str, vector: str) -> DataFrame:
    named = vectors.select(F.col(id_).cast("long").alias("id"), F.col(vector).alias("vector"))
    return named.where("id IS NOT NULL AND size(vector) > 0 AND NOT exists(vector, x -> x IS NULL)")


def cosine_join(vectors: DataFrame, id_: str, vector: str, least: float) -> DataFrame:
    """``(u, v)``, u < v: ids of all pairs of rows whose vectors have a cosine of at least ``least``.

    Exact: every pair is compared, as products of matrices. Rows are dealt to blocks by their number in reading order, and each pair of
    blocks is one group, so that no group grows with the input or with a vector that many rows share. Vectors of different
    lengths, null ones and those with a null component are in no pair; a vector of zeros, or with a component that is no finite
    number, has no number as its cosine, which counts as large, as it does in SQL.
    """
    spark = vectors.sparkSession
    usable = _usable(vectors, id_, vector)
    rows = Kept(usable.select("id", "vector", F.size("vector").alias("d"), F.monotonically_increasing_id().alias("row")), "vectors").df
    n = rows.count()
    # At least as many pairs of blocks as tasks can run at once.
    blocks = max(1, math.ceil(n / BLOCK_ROWS), min(math.ceil(n / TILE_ROWS), math.ceil(math.sqrt(4 * spark.sparkContext.defaultParallelism))))
    block = F.pmod(F.xxhash64("row"), F.lit(blocks)).cast("int").alias("block")
    others = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other")
    met = rows.select("id", "vector", "d", block).select("*", others)
    dealt = met.select("d", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), (F.col("block") > F.col("other")).alias("right"), "id", "vector")
    return dealt.groupBy("d", "i", "j").applyInArrow(_near_pairs(least, "u,v"), "u long, v long")


def cosine_links(vectors: DataFrame, id_: str, vector: str, least: float) -> DataFrame:
    """Links ``(u, v)`` with the components of ``cosine_join``: rows of equal vectors are tied to the smallest id of them, which alone is compared."""
    if not least < 0.999:
        raise ValueError("equal vectors are taken as near: least must stay below 1")
    usable = _usable(vectors, id_, vector)
    classes = Kept(usable.groupBy("vector").agg(F.min("id").alias("least")), "classes").df
    copies = usable.join(classes, "vector").where("id <> least").select(F.col("least").alias("u"), F.col("id").alias("v"))
    return copies.unionByName(cosine_join(classes, "least", "vector", least))
