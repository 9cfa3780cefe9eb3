"""Shortest and best paths over triples (row, col, val): single source, all pairs, with potentials, towards a target."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegraph.functions.semiring import MIN_PLUS, Semiring
from sparsegraph.plans.state import materialise

from .kernels import ewise_add, identity, spgemm

DENSE_LIMIT = 5_000


def relax(a: DataFrame, start: DataFrame, sr: Semiring = MIN_PLUS, *, max_rounds: int | None = None, keep=None) -> DataFrame:
    """(source, id, dist): the best path value from start (source, id, dist) to every vertex. Only improved vertices are
    active in a round. Without a fixed point after as many rounds as there are vertices, there is an improving cycle: an
    error. keep(front, best) may drop active rows."""
    edges = materialise(a.select("row", "col", F.col("val").cast("double").alias("val")), "edges")
    best = materialise(start.select("source", "id", F.col("dist").cast("double").alias("dist")), "best")
    front = best
    rounds = max_rounds
    if rounds is None:
        rounds = edges.select(F.col("row").alias("v")).union(edges.select("col")).distinct().count() + 1
    better = (lambda n, o: n < o) if sr.add is F.min else (lambda n, o: n > o)
    for _ in range(rounds):
        go = front.select("source", F.col("id").alias("row"), "dist").join(edges, "row").select("source", F.col("col").alias("id"), sr.mult(F.col("dist"), F.col("val")).alias("dist"))
        new = go.groupBy("source", "id").agg(sr.add(F.col("dist")).alias("new"))
        both = new.join(best, ["source", "id"], "left").where(F.col("dist").isNull() | better(F.col("new"), F.col("dist")))
        front = both.select("source", "id", F.col("new").alias("dist"))
        if keep is not None:
            front = keep(front, best)
        front = materialise(front, "front")
        if front.isEmpty():
            return best
        best = materialise(best.unionByName(front).groupBy("source", "id").agg(sr.add(F.col("dist")).alias("dist")), "best")
    if max_rounds is None:
        raise ValueError("a cycle improves without end")
    return best


def single(a: DataFrame, source, one: float = 0.0) -> DataFrame:
    kind = dict(a.dtypes)["row"]
    return a.sparkSession.createDataFrame([(source, source, float(one))], f"source {kind}, id {kind}, dist double")


def bellman_ford(a: DataFrame, source) -> DataFrame:
    """(id, dist) from one source; negative weights are allowed, negative cycles are an error."""
    return relax(a, single(a, source)).select("id", "dist")


def best_path(a: DataFrame, source, sr: Semiring) -> DataFrame:
    """(id, dist) under another semiring: widest (max-min), most reliable (max-times), critical path (max-plus, no cycles)."""
    return relax(a, single(a, source, float(sr.one)), sr).select("id", "dist")


def apsp(a: DataFrame, vertices: DataFrame, *, keep=lambda d: materialise(d, "apsp")) -> DataFrame:
    """(row, col, val): shortest distances of all pairs by min-plus squaring of I + A; log2(n) products. An all-pairs
    result has up to n squared rows: for small or sparse graphs."""
    d = keep(ewise_add(a.select("row", "col", F.col("val").cast("double").alias("val")), identity(vertices).withColumn("val", F.lit(0.0)), MIN_PLUS))
    n, hops = vertices.count(), 1
    while hops < n - 1:
        new = keep(spgemm(d, d, MIN_PLUS))
        same = new.join(d.withColumnRenamed("val", "_o"), ["row", "col"], "left").where("_o is null or val < _o").isEmpty()
        d, hops = new, 2 * hops
        if same:
            break
    return d


def floyd_warshall(a: DataFrame, vertices: DataFrame) -> DataFrame:
    """(row, col, val) as apsp, by the dense cubic recurrence on the driver: at most 5,000 vertices."""
    keys = [r["id"] for r in vertices.select("id").distinct().orderBy("id").limit(DENSE_LIMIT + 1).collect()]
    if len(keys) > DENSE_LIMIT:
        raise ValueError(f"the dense recurrence is for at most {DENSE_LIMIT} vertices")
    at = {k: i for i, k in enumerate(keys)}
    d = np.full((len(keys),) * 2, np.inf)
    np.fill_diagonal(d, 0.0)
    for r in a.collect():
        i, j = at[r["row"]], at[r["col"]]
        d[i, j] = min(d[i, j], float(r["val"]))
    for k in range(len(keys)):
        np.minimum(d, d[:, k : k + 1] + d[k], out=d)
    if (np.diag(d) < 0).any():
        raise ValueError("a cycle improves without end")
    kind = dict(vertices.dtypes)["id"]
    return a.sparkSession.createDataFrame([(keys[i], keys[j], float(d[i, j])) for i, j in zip(*np.nonzero(np.isfinite(d)), strict=True)], f"row {kind}, col {kind}, val double")


def johnson(a: DataFrame, vertices: DataFrame, sources: DataFrame | None = None) -> DataFrame:
    """(row, col, val): distances from the sources (all vertices by default) with negative weights: potentials from an
    extra source make every weight nonnegative, then one multi-source search runs on the new weights."""
    ids = vertices.select("id")
    zero = ids.select(F.lit(0).cast("bigint").alias("source"), "id", F.lit(0.0).alias("dist"))
    h = materialise(relax(a, zero).select("id", F.col("dist").alias("h")), "potential")
    w = a.join(h.select(F.col("id").alias("row"), F.col("h").alias("hr")), "row").join(h.select(F.col("id").alias("col"), F.col("h").alias("hc")), "col").select("row", "col", (F.col("val") + F.col("hr") - F.col("hc")).alias("val"))
    src = (sources if sources is not None else ids).select("id")
    d = relax(w, src.select(F.col("id").alias("source"), "id", F.lit(0.0).alias("dist")))
    return d.join(h.select(F.col("id").alias("source"), F.col("h").alias("hr")), "source").join(h.select("id", F.col("h").alias("hc")), "id").select(F.col("source").alias("row"), F.col("id").alias("col"), (F.col("dist") - F.col("hr") + F.col("hc")).alias("val"))


def landmark_bound(a: DataFrame, target, landmarks: list) -> DataFrame:
    """(id, h): a lower bound of the distance to the target, from distances to and from landmarks (triangle inequality)."""
    out = None
    rev = a.select(F.col("col").alias("row"), F.col("row").alias("col"), "val")
    for m in landmarks:
        to = bellman_ford(rev, m).withColumnRenamed("dist", "to")  # distance of each vertex to the landmark
        t = to.where(F.col("id") == F.lit(target)).select("to").first()
        if t is None:
            continue
        part = to.select("id", F.greatest(F.col("to") - F.lit(t["to"]), F.lit(0.0)).alias("h"))
        out = part if out is None else out.unionByName(part)
    if out is None:
        return a.sparkSession.createDataFrame([], f"id {dict(a.dtypes)['row']}, h double")
    return out.groupBy("id").agg(F.max("h").alias("h"))


def astar(a: DataFrame, source, target, h: DataFrame | None = None) -> float | None:
    """The distance from source to target, or None. Active vertices whose distance plus bound h (id, h) cannot beat the
    best known path to the target are dropped; without h this is a plain search with pruning."""
    bound = materialise(h, "bound") if h is not None else None

    def keep(front: DataFrame, best: DataFrame) -> DataFrame:
        known = best.unionByName(front).where(F.col("id") == F.lit(target)).agg(F.min("dist")).first()[0]
        if known is None:
            return front
        f = front.join(bound, "id", "left") if bound is not None else front.withColumn("h", F.lit(0.0))
        return f.where((F.col("dist") + F.coalesce("h", F.lit(0.0)) < F.lit(known)) | (F.col("id") == F.lit(target))).select("source", "id", "dist")

    r = relax(a, single(a, source), keep=keep).where(F.col("id") == F.lit(target)).first()
    return None if r is None else r["dist"]
