"""Degree, eigenvector, Katz, PageRank, betweenness and closeness centrality over triples (row, col, val)."""

from __future__ import annotations

from collections.abc import Callable
from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegraph.plans.iterate import IterationReport, fixpoint
from sparsegraph.plans.state import materialise

from .kernels import reduce_cols, reduce_rows, transpose


def endpoints(a: DataFrame) -> DataFrame:
    return a.select(F.col("row").alias("id")).union(a.select("col")).distinct()


def degree(a: DataFrame, kind: str = "out", *, weighted: bool = False, vertices: DataFrame | None = None) -> DataFrame:
    """(id, degree): row sums (out), column sums (in) or both (total) of entries, or of their number. A vertex table adds
    the vertices without edges."""
    if not weighted:
        a = a.withColumn("val", F.lit(1).cast("bigint"))
    if kind == "total":
        d = reduce_rows(a).unionByName(reduce_cols(a)).groupBy("id").agg(F.sum("val").alias("degree"))
    else:
        d = (reduce_rows if kind == "out" else reduce_cols)(a).withColumnRenamed("val", "degree")
    if vertices is None:
        return d
    return vertices.select("id").join(d, "id", "left").select("id", F.coalesce("degree", F.lit(0)).alias("degree"))


def _cosine_stop(tol: float):
    def stop(m: dict) -> str | None:
        if not m["new"]:
            return "vanished"
        return "converged" if 1 - m["dot"] / (m["old"] * m["new"]) ** 0.5 < tol else None

    return stop


def _norms(state: DataFrame, _: int) -> dict:
    r = state.agg(F.sum(F.col("x") * F.col("prev")).alias("dot"), F.sum(F.col("prev") * F.col("prev")).alias("old"), F.sum(F.col("x") * F.col("x")).alias("new")).first()
    return {k: float(r[k] or 0.0) for k in ("dot", "old", "new")}


def eigenvector(a: DataFrame, *, tol: float = 1e-8, max_iter: int = 100, shift: float = 0.0, direction: str = "out", x0: DataFrame | None = None, vertices: DataFrame | None = None, fixed_steps: int | None = None) -> tuple[DataFrame, IterationReport]:
    """(id, score), of length 1, by the power method with A + shift I; stops on the cosine of successive vectors, or
    after fixed_steps. direction "in" iterates with the transpose. A shift makes bipartite graphs converge."""
    a = materialise((a if direction == "out" else transpose(a)).select("row", "col", F.col("val").cast("double").alias("val")), "matrix")
    ids = vertices.select("id") if vertices is not None else endpoints(a)
    start = ids.join(x0.select("id", F.col("val").alias("x")), "id", "left").select("id", F.coalesce("x", F.lit(0.0)).alias("x")) if x0 is not None else ids.withColumn("x", F.lit(1.0))
    norm = {"x": 1.0}

    def step(s: DataFrame, _: int) -> DataFrame:
        # Division by the last known norm keeps numbers in range; the direction does not depend on it.
        prev = s.select("id", (F.col("x") / F.lit(norm["x"])).alias("prev"))
        y = a.join(prev.select(F.col("id").alias("col"), "prev"), "col").groupBy(F.col("row").alias("id")).agg(F.sum(F.col("val") * F.col("prev")).alias("y"))
        return prev.join(y, "id", "left").select("id", "prev", (F.coalesce("y", F.lit(0.0)) + F.lit(float(shift)) * F.col("prev")).alias("x"))

    def measure(s: DataFrame, k: int) -> dict:
        m = _norms(s, k)
        norm["x"] = m["new"] ** 0.5 or 1.0
        return m

    stop = _cosine_stop(-1.0 if fixed_steps else tol)
    first = start.withColumn("prev", F.lit(0.0))
    state, report = fixpoint(first, step, measure, stop, max_iter=fixed_steps or max_iter, name="power")
    return state.select("id", (F.col("x") / F.lit(norm["x"])).alias("score")), report


def max_degree_bound(a: DataFrame) -> float:
    """An upper bound of the spectral radius of a nonnegative matrix."""
    r = reduce_rows(a).agg(F.max("val").alias("m")).first()["m"]
    c = reduce_cols(a).agg(F.max("val").alias("m")).first()["m"]
    return float(min(r or 0, c or 0))


def katz(a: DataFrame, alpha: float, *, x0: float = 0.0, scaled: bool = False, tol: float = 1e-10, max_iter: int = 200, vertices: DataFrame | None = None, fixed_steps: int | None = None, check: bool = True) -> tuple[DataFrame, IterationReport]:
    """(id, score): path counts of every length, damped by alpha for each further step. State and accumulator travel in
    one table. An alpha that the degree bound does not prove convergent is an error unless check is off."""
    if check and alpha * (bound := max_degree_bound(a)) >= 1:
        raise ValueError(f"alpha {alpha} is not below 1 / {bound}, the bound of the largest eigenvalue")
    a = materialise(a.select("row", "col", F.col("val").cast("double").alias("val")), "matrix")
    ids = vertices.select("id") if vertices is not None else endpoints(a)

    def step(s: DataFrame, _: int) -> DataFrame:
        y = a.join(s.select(F.col("id").alias("col"), "e"), "col").groupBy(F.col("row").alias("id")).agg(F.sum(F.col("val") * F.col("e")).alias("term"))
        term = F.coalesce("term", F.lit(0.0))
        return s.join(y, "id", "left").select("id", F.col("x").alias("prev"), (F.col("x") + term).alias("x"), (F.lit(alpha) * term).alias("e"))

    def measure(s: DataFrame, k: int) -> dict:
        m = _norms(s, k)
        m["step"] = float(s.agg(F.sum((F.col("x") - F.col("prev")) ** 2)).first()[0] or 0.0)
        return m

    def stop(m: dict) -> str | None:
        if fixed_steps:
            return None
        if not m["new"]:
            return "vanished"
        close = m["old"] and 1 - m["dot"] / (m["old"] * m["new"]) ** 0.5 < tol
        return "converged" if close and (m["step"] / m["new"]) ** 0.5 < tol else None

    first = ids.select("id", F.lit(0.0).alias("prev"), F.lit(float(x0)).alias("x"), F.lit(1.0).alias("e"))
    state, report = fixpoint(first, step, measure, stop, max_iter=fixed_steps or max_iter, name="katz")
    return state.select("id", (F.col("x") * F.lit(alpha if scaled else 1.0)).alias("score")), report


def pagerank(a: DataFrame, *, jump: float = 0.15, dangling: str = "uniform", tol: float = 1e-10, max_iter: int = 100, vertices: DataFrame | None = None, personalization: DataFrame | None = None, fixed_steps: int | None = None, explicit_ones: bool = False) -> tuple[DataFrame, IterationReport]:
    """(id, score) with sum 1. jump is the chance to leave for any vertex (or for personalization, id and val). The matrix of ones
    is never formed: its product is the sum of the vector, one number (explicit_ones forms it, as a baseline for small
    graphs). dangling: what vertices without out-edges do: uniform, self, or drop (their mass is lost, then rescaled)."""
    ids = materialise(vertices.select("id") if vertices is not None else endpoints(a), "vertices")
    n = ids.count()
    out = a.groupBy("row").agg(F.sum("val").alias("_d"))
    p = materialise(a.join(out, "row").select("row", "col", (F.col("val").cast("double") / F.col("_d")).alias("p")), "walk")
    base = ids.withColumn("home", F.lit(1.0 / max(n, 1)))
    if personalization is not None:
        total = float(personalization.agg(F.sum("val")).first()[0])
        base = ids.join(personalization.select("id", (F.col("val").cast("double") / total).alias("_h")), "id", "left").select("id", F.coalesce("_h", F.lit(0.0)).alias("home"))
    base = base.join(out.select(F.col("row").alias("id"), F.lit(False).alias("_e")), "id", "left").select("id", "home", F.coalesce("_e", F.lit(True)).alias("end"))
    if explicit_ones and n > 5000:
        raise ValueError("the explicit matrix of ones is for at most 5000 vertices")
    lost = {"sum": 1.0, "end": None}

    def step(s: DataFrame, _: int) -> DataFrame:
        y = p.join(s.select(F.col("id").alias("row"), "x"), "row").groupBy(F.col("col").alias("id")).agg(F.sum(F.col("p") * F.col("x")).alias("y"))
        if lost["end"] is None:
            lost["end"] = float(s.where("end").agg(F.sum("x")).first()[0] or 0.0)
        keep = F.coalesce("y", F.lit(0.0))
        if dangling == "uniform":
            keep = keep + F.lit(lost["end"]) * F.col("home")
        elif dangling == "self":
            keep = keep + F.when(F.col("end"), F.col("x")).otherwise(0.0)
        joined = s.join(y, "id", "left")
        if explicit_ones:
            jumped = s.select(F.col("id").alias("_i")).crossJoin(s.select(F.col("x").alias("_x"))).groupBy("_i").agg(F.sum("_x").alias("_s"))
            joined = joined.join(jumped, F.col("id") == F.col("_i"))
            every = F.col("_s")
        else:
            every = F.lit(lost["sum"])
        return joined.select("id", "home", "end", F.col("x").alias("prev"), (F.lit(float(jump)) * every * F.col("home") + F.lit(1.0 - jump) * keep).alias("x"))

    def measure(s: DataFrame, _: int) -> dict:
        r = s.agg(F.sum(F.col("x") * F.col("prev")).alias("dot"), F.sum(F.col("prev") * F.col("prev")).alias("old"), F.sum(F.col("x") * F.col("x")).alias("new"), F.sum("x").alias("sum"), F.sum(F.when(F.col("end"), F.col("x"))).alias("end"), F.sum(F.abs(F.col("x") - F.col("prev"))).alias("l1")).first()
        m = {k: float(r[k] or 0.0) for k in ("dot", "old", "new", "sum", "end", "l1")}
        lost.update(sum=m["sum"], end=m["end"])
        return m

    first = base.select("id", "home", "end", F.lit(0.0).alias("prev"), F.lit(1.0 / max(n, 1)).alias("x"))
    cosine = _cosine_stop(tol)
    state, report = fixpoint(first, step, measure, (lambda m: None) if fixed_steps else cosine, max_iter=fixed_steps or max_iter, name="pagerank")
    total = lost["sum"] if dangling == "drop" else 1.0
    return state.select("id", (F.col("x") / F.lit(total or 1.0)).alias("score")), report


def bfs_levels(a: DataFrame, sources: DataFrame) -> DataFrame:
    """(source, id, level, paths): levels and numbers of shortest paths from every source at once."""
    edges = materialise(a.select("row", "col").distinct(), "edges")
    front = sources.select(F.col("id").alias("source"), "id", F.lit(0).alias("level"), F.lit(1.0).alias("paths"))
    seen = materialise(front, "bfs")
    front = seen
    for depth in count(1):
        reached = front.join(edges.withColumnRenamed("row", "id"), "id").groupBy("source", F.col("col").alias("id")).agg(F.sum("paths").alias("paths"))
        front = materialise(reached.join(seen.select("source", "id"), ["source", "id"], "left_anti").select("source", "id", F.lit(depth).alias("level"), "paths"), "front")
        if front.isEmpty():
            break
        seen = seen.unionByName(front)
        if depth % 8 == 0:
            seen = materialise(seen, "bfs")
    return seen


def betweenness(a: DataFrame, sources: DataFrame | None = None, *, directed: bool = False, normalized: bool = False, vertices: DataFrame | None = None) -> DataFrame:
    """(id, score): share of shortest paths through each vertex, from all sources (or the given ones, which samples at
    scale). A forward sweep counts paths by level, a backward sweep hands dependencies up level by level."""
    ids = vertices.select("id") if vertices is not None else endpoints(a)
    found = materialise(bfs_levels(a, sources if sources is not None else ids), "paths")
    edges = a.select("row", "col").distinct()
    deepest = found.agg(F.max("level")).first()[0] or 0
    dep = found.where(F.col("level") == deepest).select("source", "id", F.lit(0.0).alias("dep"))
    total = dep
    for level in range(deepest, 0, -1):
        low = found.where(F.col("level") == level).join(dep, ["source", "id"]).select("source", F.col("id").alias("col"), ((F.lit(1.0) + F.col("dep")) / F.col("paths")).alias("share"))
        up = found.where(F.col("level") == level - 1)
        got = up.join(edges.withColumnRenamed("row", "id"), "id").join(low, ["source", "col"]).groupBy("source", "id").agg(F.sum(F.col("paths") * F.col("share")).alias("dep"))
        dep = materialise(up.join(got, ["source", "id"], "left").select("source", "id", F.coalesce("dep", F.lit(0.0)).alias("dep")), "dependency")
        total = total.unionByName(dep)
    score = total.where("source <> id").groupBy("id").agg(F.sum("dep").alias("score"))
    factor = 1.0 if directed else 0.5
    if normalized:
        n = ids.count()
        factor = factor * (2.0 if not directed else 1.0) / max((n - 1) * (n - 2), 1)
    return ids.join(score, "id", "left").select("id", (F.coalesce("score", F.lit(0.0)) * factor).alias("score"))


def closeness(a: DataFrame, sources: DataFrame | None = None, *, harmonic: bool = False, vertices: DataFrame | None = None) -> DataFrame:
    """(id, score) of the sources: reached vertices over the sum of their distances, or the sum of inverse distances."""
    ids = vertices.select("id") if vertices is not None else endpoints(a)
    found = bfs_levels(a, sources if sources is not None else ids).where("level > 0")
    value = F.sum(1 / F.col("level")) if harmonic else F.count("*") / F.sum("level")
    return (sources if sources is not None else ids).select("id").join(found.groupBy(F.col("source").alias("id")).agg(value.cast("double").alias("score")), "id", "left").select("id", F.coalesce("score", F.lit(0.0)).alias("score"))


def by_source_blocks(a: DataFrame, measure: Callable[[DataFrame, DataFrame], DataFrame], cells: int = 50_000_000) -> DataFrame:
    """(id, score) summed over blocks of sources that together are all vertices. A block has so many sources that it
    reaches about `cells` pairs of source and vertex at most; blocks run one after the other against all edges."""
    ids = materialise(endpoints(a).select("id"), "vertices")
    n = ids.count()
    blocks = max(1, -(-n * n // cells))
    dealt = materialise(ids.withColumn("_b", F.pmod(F.xxhash64("id"), F.lit(blocks))), "blocks")
    total = None
    for b in range(blocks):
        part = measure(a, dealt.where(F.col("_b") == b).select("id"))
        total = part if total is None else total.unionByName(part)
        # The written sum keeps the plan short.
        total = materialise(total.groupBy("id").agg(F.sum("score").alias("score")), "block-sum")
    return total
