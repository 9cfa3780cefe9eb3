"""Cliques, vertex nomination, planted cliques and clusters, connected components."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from sparsegraph.plans.state import materialise

from .centrality import pagerank
from .components import components  # noqa: F401
from .schema import both_ways, simple_graph
from .similarity import jaccard
from .truss import k_truss, with_ids


def k_cliques(edges: DataFrame, k: int, *, prune: bool = True) -> DataFrame:
    """(v1 < ... < vk): all cliques of k vertices, grown one vertex at a time. A k-clique lies in the k-truss, so for
    k > 3 the truss is taken first."""
    if prune and k > 3:
        edges = k_truss(with_ids(edges), k)[0]
    e = materialise(edges.select("src", "dst"), "edges")
    out = e.toDF("v1", "v2")
    for n in range(3, k + 1):
        out = out.join(e.toDF(f"v{n - 1}", f"v{n}"), f"v{n - 1}")
        for i in range(1, n - 1):
            out = out.join(e.toDF(f"v{i}", f"v{n}"), [f"v{i}", f"v{n}"], "left_semi")
        out = materialise(out.select(*[f"v{i}" for i in range(1, n + 1)]), "cliques")
    return out


def maximal_cliques(edges: DataFrame, max_size: int = 8) -> DataFrame:
    """(size, members): cliques of 2 to max_size vertices that no vertex extends. Larger ones show up as their parts of
    max_size vertices, marked by size = max_size."""
    n = both_ways(edges).select("row", "col")
    out = None
    for k in range(2, max_size + 1):
        c = k_cliques(edges, k, prune=k > 3)
        if c.isEmpty():
            break
        vs = [f"v{i}" for i in range(1, k + 1)]
        c = c.withColumn("members", F.array(*vs))
        if k < max_size:
            wider = c.select("members", F.explode("members").alias("row")).join(n, "row").groupBy("members", "col").agg(F.count("*").alias("n")).where(F.col("n") == k).select("members").distinct()
            c = c.join(wider, "members", "left_anti")
        c = c.select(F.lit(k).alias("size"), "members")
        out = c if out is None else out.unionByName(c)
    return out


def nominate(a: DataFrame, cues: DataFrame, method: str = "neighbors", *, top: int | None = None) -> DataFrame:
    """(id, score, rank): vertices that are not cues, ranked by how close they are to the cues: summed weights of edges
    from cues (neighbors), a walk that restarts at cues (ppr), or the best Jaccard index with a cue (jaccard)."""
    seeds = cues.select("id").distinct()
    if method == "neighbors":
        s = a.join(seeds.withColumnRenamed("id", "row"), "row", "left_semi").groupBy(F.col("col").alias("id")).agg(F.sum("val").cast("double").alias("score"))
    elif method == "ppr":
        s = pagerank(a, jump=0.15, personalization=seeds.withColumn("val", F.lit(1.0)), tol=1e-9)[0]
    elif method == "jaccard":
        g = simple_graph(a, "row", "col")
        j = jaccard(g, symmetric=True).join(seeds.withColumnRenamed("id", "i"), "i", "left_semi")
        s = j.groupBy(F.col("j").alias("id")).agg(F.max("score").alias("score"))
    else:
        raise ValueError(method)
    s = s.join(seeds, "id", "left_anti")
    order = [F.col("score").desc(), F.col("id")]
    if top is not None:
        s = s.orderBy(*order).limit(top)
        return s.withColumn("rank", F.row_number().over(W.orderBy(*order)))  # at most `top` rows
    return s.withColumn("rank", F.lit(None).cast("int"))


def residual_vector(edges: DataFrame, steps: int = 12) -> DataFrame:
    """(id, x): leading eigenvector of A - d d^T / 2m; the residual matrix is never formed, its product is a sparse product
    less a scalar times the degrees."""
    a = materialise(both_ways(edges), "adjacency")
    deg = materialise(a.groupBy(F.col("row").alias("id")).agg(F.sum("val").cast("double").alias("d")), "degree")
    m2 = float(deg.agg(F.sum("d")).first()[0] or 1.0)
    s = deg.select("id", "d", (F.pmod(F.xxhash64("id"), F.lit(1000)) / 1000.0 + 0.5).alias("x"))
    for k in range(steps):
        s = materialise(s, "residual")
        r = s.agg(F.sum(F.col("d") * F.col("x")).alias("dx"), F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("n")).first()
        y = a.join(s.select(F.col("id").alias("col"), "x"), "col").groupBy(F.col("row").alias("id")).agg(F.sum("x").alias("y"))
        # A shift by the identity keeps the largest positive eigenvalue ahead of the negative ones.
        s = s.join(y, "id").select("id", "d", ((F.col("y") - F.col("d") * F.lit(r["dx"] / m2) + F.col("x")) / F.lit(r["n"] or 1.0)).alias("x"))
    return s.select("id", "x")


def planted_clique(edges: DataFrame, k: int, method: str = "truss") -> DataFrame:
    """(id): suspected members of a planted clique of about k vertices: the ends of the k-truss; the k vertices of the
    highest degree; or the k largest entries of the residual eigenvector. degree and spectral end with the truss of what
    they chose, where it is not empty."""
    if method == "truss":
        t = k_truss(with_ids(edges), k)[0]
        return t.select(F.col("src").alias("id")).union(t.select("dst")).distinct()
    if method == "degree":
        best = both_ways(edges).groupBy(F.col("row").alias("id")).agg(F.count("*").alias("s"))
    elif method == "spectral":
        best = residual_vector(edges).select("id", F.abs("x").alias("s"))
    else:
        raise ValueError(method)
    pick = best.orderBy(F.col("s").desc(), "id").limit(2 * k).select("id")
    inner = edges.join(pick.withColumnRenamed("id", "src"), "src", "left_semi").join(pick.withColumnRenamed("id", "dst"), "dst", "left_semi")
    t = materialise(planted_clique(simple_graph(inner), max(3, int(0.8 * k)), "truss"), "clique")
    return pick if t.isEmpty() else t


def planted_cluster(edges: DataFrame, size: int) -> DataFrame:
    """(id, x): the `size` largest entries of the residual eigenvector, on the side of the larger sum."""
    v = materialise(residual_vector(edges), "vector")
    side = v.agg(F.sum(F.when(F.col("x") > 0, F.col("x") ** 3).otherwise(0)).alias("p"), F.sum(F.when(F.col("x") < 0, -(F.col("x") ** 3)).otherwise(0)).alias("n")).first()
    sign = 1 if (side["p"] or 0) >= (side["n"] or 0) else -1
    return v.orderBy((F.col("x") * sign).desc(), "id").limit(size).select("id", "x")


def plant(edges: DataFrame, k: int, *, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """(edges with a clique among k vertices, the vertices): those whose ids hash lowest."""
    v = both_ways(edges).select(F.col("row").alias("id")).distinct().orderBy(F.xxhash64(F.lit(seed), "id"), "id").limit(k)
    v = materialise(v, "planted")
    clique = v.select(F.col("id").alias("src")).join(v.select(F.col("id").alias("dst")), F.expr("src < dst"))
    return edges.select("src", "dst").union(clique).distinct(), v
