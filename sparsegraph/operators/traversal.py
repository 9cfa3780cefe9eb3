"""Breadth-first and depth-first search over triples (row, col, val)."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsegraph.plans.state import materialise

DFS_LIMIT = 1_000_000


def bfs(a: DataFrame, sources: DataFrame, *, max_depth: int | None = None) -> DataFrame:
    """(source, id, level, parent): shortest hop counts from each source; parent is the smallest predecessor on a shortest
    path (null at the source). The visited set is an anti-join mask. The search ends when nothing new is reached, or with
    max_depth at that level."""
    edges = materialise(a.select("row", "col").distinct(), "edges")
    seen = materialise(sources.select(F.col("id").alias("source"), "id", F.lit(0).alias("level"), F.lit(None).cast(dict(sources.dtypes)["id"]).alias("parent")), "bfs")
    front = seen
    for depth in count(1) if max_depth is None else range(1, max_depth + 1):
        reached = front.select("source", F.col("id").alias("row")).join(edges, "row").groupBy("source", F.col("col").alias("id")).agg(F.min("row").alias("parent"))
        front = materialise(reached.join(seen.select("source", "id"), ["source", "id"], "left_anti").select("source", "id", F.lit(depth).alias("level"), "parent"), "front")
        if front.isEmpty():
            break
        seen = seen.unionByName(front)
        if depth % 8 == 0:
            seen = materialise(seen, "bfs")
    return seen


def bfs_sql(spark: SparkSession, view: str, source: int, depth: int) -> DataFrame:
    """(id, level) from one source up to a depth, as a recursive SQL query over a view (row, col)."""
    return spark.sql(
        f"WITH RECURSIVE r(id, level) AS (SELECT CAST({int(source)} AS BIGINT), 0 UNION ALL SELECT e.col, r.level + 1 FROM r JOIN {view} e ON e.row = r.id WHERE r.level < {int(depth)}) "
        "SELECT id, min(level) AS level FROM r GROUP BY id"
    )


def dfs(a: DataFrame, source: int, *, limit: int = DFS_LIMIT) -> DataFrame:
    """(id, pre, post): visit order from the source, neighbours by id. The order is sequential by nature: the edges
    reachable from the source go to one task, at most `limit` of them."""
    reach = bfs(a, a.sparkSession.createDataFrame([(source,)], "id bigint")).select(F.col("id").alias("row"))
    edges = a.select("row", "col").distinct().join(reach, "row", "left_semi")
    if edges.limit(limit + 1).count() > limit:
        raise ValueError(f"depth-first search is for at most {limit} edges")

    def walk(pdf):
        import pandas as pd

        near: dict = {}
        for r, c in zip(pdf["row"].tolist(), pdf["col"].tolist(), strict=True):
            near.setdefault(r, []).append(c)
        for v in near.values():
            v.sort(reverse=True)
        pre, post, stack = {source: 0}, {}, [source]
        while stack:
            v = stack[-1]
            rest = near.get(v, [])
            while rest and rest[-1] in pre:
                rest.pop()
            if rest:
                pre[rest[-1]] = len(pre)
                stack.append(rest[-1])
            else:
                post[v] = len(post)
                stack.pop()
        return pd.DataFrame({"id": list(pre), "pre": list(pre.values()), "post": [post[v] for v in pre]})

    found = edges.withColumn("_g", F.lit(0)).groupBy("_g").applyInPandas(walk, "id bigint, pre bigint, post bigint")
    return found if not edges.isEmpty() else a.sparkSession.createDataFrame([(source, 0, 0)], "id bigint, pre bigint, post bigint")
