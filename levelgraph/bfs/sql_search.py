"""The plain-SQL baseline: one statement whose levels are chained table expressions.

Spark's recursive queries keep every walk (only ``UNION ALL``, no grouping on the recursion), so their
rows grow with the number of walks, which two steps over a hub already square; a session ends such a
query beyond its row limit.  Here each level groups what the one before reached, so it holds a row a
vertex at most.  It expands everything reached again in each level; the searches in
:mod:`levelgraph.bfs.hybrid` are what to use.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame

from levelgraph.graph.build import Graph


def recursive_depths(graph: Graph, source: int, max_depth: int) -> DataFrame:
    """``v, depth`` of the vertices within ``max_depth`` of ``source``, in one SQL statement."""
    view = f"arcs_{uuid.uuid4().hex}"
    graph.arcs.createOrReplaceTempView(view)
    levels = [f"l0 as (select cast({int(source)} as bigint) as v, 0 as depth)"]
    for k in range(1, int(max_depth) + 1):
        # a row stays and meets its neighbours in one pass, so each level is read once
        levels.append(
            f"""l{k} as (select x.v, min(x.depth) as depth from (
            select inline(array(struct(l.v as v, l.depth as depth), struct(coalesce(a.dst, l.v) as v, l.depth + if(a.dst is null, 0, 1) as depth)))
            from l{k - 1} l left join {view} a on a.src = l.v) x group by x.v)"""
        )
    return graph.spark.sql(f"with {', '.join(levels)} select v, depth from l{int(max_depth)}")
