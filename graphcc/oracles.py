"""DuckDB texts for the component queries."""

from __future__ import annotations

from graphcc.sources.workloads import EDGES, duck_sql, scrambled, turn_id


def components_sql(edges_sql: str) -> str:
    """Components of any edge query (u, v): keep the best label of a node, replaced by smaller ones of its neighbours."""
    return f"""
WITH RECURSIVE e AS ({edges_sql}),
s AS (SELECT DISTINCT u, v FROM e WHERE u <> v UNION SELECT DISTINCT v, u FROM e WHERE u <> v),
cc(node, component) USING KEY (node) AS (
  SELECT u, min(least(u, v)) FROM s GROUP BY u
  UNION
  SELECT s.v, min(cc.component) FROM cc JOIN s ON s.u = cc.node JOIN recurring.cc r ON r.node = s.v WHERE cc.component < r.component GROUP BY s.v)
SELECT node, component FROM cc"""


_CLOSED = {
    "w1": """SELECT node, min(node) OVER (PARTITION BY c) AS component FROM
    (SELECT o_orderkey * 2 + 1 AS node, o_custkey AS c FROM orders UNION SELECT o_custkey * 2, o_custkey FROM orders) x""",
    "w5": "SELECT vec_id AS node, min(vec_id) OVER (PARTITION BY label) AS component FROM embeddings QUALIFY count(*) OVER (PARTITION BY label) > 1",
    "w6": "SELECT event_id AS node, min(event_id) OVER (PARTITION BY user_id) AS component FROM events QUALIFY count(*) OVER (PARTITION BY user_id) > 1",
    "w7": "SELECT event_id AS node, min(event_id) OVER () AS component FROM events",
    "w8": f"SELECT {scrambled('event_id')} AS node, min({scrambled('event_id')}) OVER () AS component FROM events",
    "w11": f"SELECT {turn_id()} AS node, min({turn_id()}) OVER (PARTITION BY conv_id) AS component FROM conversations QUALIFY count(*) OVER (PARTITION BY conv_id) > 1",
}



def workload_sql(name: str) -> str:
    """Oracle of a workload: a closed form where there is one."""
    return _CLOSED.get(name) or components_sql(duck_sql(EDGES[name]))
