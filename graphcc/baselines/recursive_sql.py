"""Components by a recursive SQL query, for small components: every walk up from a node that may be the smallest is a row."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

from graphcc.session import Kept


@contextmanager
def _any_rows(spark: SparkSession) -> Iterator[None]:
    """Inside, recursion may make as many rows as the walks need; the session's own limit holds again afterwards."""
    name = "spark.sql.cteRecursionRowLimit"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "-1")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def _walked(spark: SparkSession, view: str, depth: int) -> DataFrame:
    # The smallest node of a component is smaller than its neighbours, and all walks from it lead to larger nodes.
    return spark.sql(f"""
        WITH RECURSIVE
        reach(start, other, came_from, depth) MAX RECURSION LEVEL {depth + 2} AS (
            SELECT u, u, CAST(NULL AS BIGINT), 0 FROM {view} GROUP BY u HAVING min(v) > u
            UNION ALL
            SELECT r.start, b.v, r.other, r.depth + 1 FROM reach r JOIN {view} b ON b.u = r.other
            WHERE r.depth < {depth} AND (r.came_from IS NULL OR b.v <> r.came_from) AND b.v > r.start)
        SELECT node, min(label) AS component FROM
            (SELECT other AS node, start AS label FROM reach UNION ALL SELECT DISTINCT u, u FROM {view}) x
        GROUP BY node""")


def components(edges: DataFrame, max_depth: int = 12) -> DataFrame:
    """Walks that never turn straight back, of up to ``max_depth`` steps; while an edge joins two labels, twice as many.

    Once no edge does, a label is the smallest id of its whole component. Walks are not limited in number: it grows with
    the nodes, and in components with many cycles with the ways through them.
    """
    spark, view = edges.sparkSession, f"edges_{uuid.uuid4().hex[:10]}"
    apart = edges.where("u <> v").select("u", "v")
    pairs = Kept(apart.unionAll(apart.select("v", "u")).distinct(), "pairs").df
    pairs.createOrReplaceTempView(view)
    depth = max(1, max_depth)
    while True:
        with _any_rows(spark):
            labels = Kept(_walked(spark, view, depth), "walked").df
        one, two = labels.toDF("u", "cu"), labels.toDF("v", "cv")
        if pairs.join(one, "u").join(two, "v").where("cu <> cv").isEmpty():
            return labels
        depth *= 2
