"""Edge support, k-truss and truss decomposition. Edges are (edge_id, src, dst) of a simple graph, src < dst."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegraph.plans.iterate import IterationReport
from sparsegraph.plans.state import materialise

from .kernels import apply, reduce_rows, spgemm
from .schema import both_ways, inc_to_adj, incidence


def with_ids(edges: DataFrame) -> DataFrame:
    """edge_id of a simple graph: a hash of its ends, the same in every run."""
    return edges.select(F.xxhash64("src", "dst").alias("edge_id"), "src", "dst")


def check_unit(inc: DataFrame) -> DataFrame:
    """Fails unless every edge has exactly two ends of value 1: "the cell is 2" means a triangle only then."""
    bad = inc.groupBy("row").agg(F.count("*").alias("n"), F.min("val").alias("a"), F.max("val").alias("b")).where("n <> 2 or a <> 1 or b <> 1")
    if not bad.isEmpty():
        raise ValueError("the incidence has weighted or hyper edges")
    return inc


def overlap_cells(inc: DataFrame, adj: DataFrame) -> DataFrame:
    """The product of incidence and adjacency: (row=edge, col=vertex, val = ends of the edge adjacent to the vertex)."""
    return spgemm(inc, adj)


def edge_support(edges: DataFrame, method: str = "masked") -> DataFrame:
    """(edge_id, src, dst, support): triangles on each edge, 0 included. "incidence" multiplies incidence and adjacency
    and counts the cells equal to 2; "masked" forms triangles alone, from the end of lower degree. Loops and second copies
    of an edge are dropped first (see canonical)."""
    return _support(canonical(edges), method)


def canonical(edges: DataFrame) -> DataFrame:
    """(edge_id, src, dst), src < dst: without loops and null ends, of edges between the same vertices that of the least id."""
    ends = edges.where(F.col("src") != F.col("dst")).select("edge_id", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    return ends.groupBy("src", "dst").agg(F.min("edge_id").alias("edge_id")).select("edge_id", "src", "dst")


def _support(edges: DataFrame, method: str) -> DataFrame:
    if method == "incidence":
        inc = incidence(edges)
        twos = apply(overlap_cells(inc, inc_to_adj(inc)), lambda v: F.when(v == 2, 1).otherwise(0))
        held = reduce_rows(twos, lambda c: F.count(c)).select(F.col("id").alias("edge_id"), F.col("val").alias("support"))
    elif method == "masked":
        held = triangle_edges(triangles(edges)).groupBy("edge_id").agg(F.count("*").alias("support"))
    else:
        raise ValueError(method)
    return edges.select("edge_id", "src", "dst").join(held, "edge_id", "left").select("edge_id", "src", "dst", F.coalesce("support", F.lit(0)).cast("bigint").alias("support"))


def triangles(edges: DataFrame) -> DataFrame:
    """(e1, e2, e3), the edge ids of every triangle, each once. Edges point from the lower to the higher (degree, id), so
    that no vertex has more out-edges than the root of twice the edges, hubs included."""
    ends = both_ways(edges)
    deg = ends.groupBy("row").agg(F.count("*").alias("d"))
    marked = edges.join(deg.select(F.col("row").alias("src"), F.col("d").alias("ds")), "src").join(deg.select(F.col("row").alias("dst"), F.col("d").alias("dd")), "dst")
    up = F.struct("ds", "src") < F.struct("dd", "dst")
    arcs = marked.select("edge_id", F.when(up, F.col("src")).otherwise(F.col("dst")).alias("lo"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("hi"))
    x, y = arcs.select("lo", F.col("hi").alias("u"), F.col("edge_id").alias("e1")), arcs.select("lo", F.col("hi").alias("v"), F.col("edge_id").alias("e2"))
    wedges = x.join(y, "lo").where("u < v")
    closing = edges.select(F.col("src").alias("u"), F.col("dst").alias("v"), F.col("edge_id").alias("e3"))
    return wedges.join(closing, ["u", "v"]).select("e1", "e2", "e3")


def triangle_edges(tri: DataFrame) -> DataFrame:
    return tri.select(F.explode(F.array("e1", "e2", "e3")).alias("edge_id"))


def k_truss(edges: DataFrame, k: int, *, method: str = "masked", update: str | None = None, max_rounds: int | None = None) -> tuple[DataFrame, IterationReport]:
    """(edge_id, src, dst, support) of the k-truss: weak edges (support below k - 2) go, all of a round together, until
    there are none.

    method/update: "masked" keeps the list of triangles and drops those that lose an edge ("delta"), or finds it anew
    ("recompute"); "incidence" keeps the cells of incidence times adjacency and subtracts what removed edges contributed
    ("incremental"), or multiplies anew ("recompute"); "ordered" removes the smallest support class first; "sequential"
    removes one edge at a time (at most 10,000 edges). All give the same edges. Peeling ends when nothing is weak; more than
    max_rounds rounds are an error, never a graph that is no k-truss. Edges are made canonical first."""
    report = IterationReport()
    edges = materialise(canonical(edges), "edges")
    if k <= 2:
        report.status, report.converged = "converged", True
        return _support(edges, "incidence" if method == "incidence" else "masked"), report
    if method == "incidence":
        return _peel_incidence(edges, k, update or "incremental", report, max_rounds)
    if method == "sequential" and edges.count() > 10_000:
        raise ValueError("one edge at a time is for at most 10,000 edges")
    tri = materialise(triangles(edges), "triangles")
    out, tri = _peel(edges, tri, k, method, update or "delta", report, max_rounds)
    return out, report


def _rounds(most: int | None):
    """0, 1, ...; an error beyond `most` rounds."""
    for k in count():
        if most is not None and k > most:
            raise RuntimeError(f"peeling did not end in {most} rounds")
        yield k


def _counted(edges: DataFrame, tri: DataFrame) -> DataFrame:
    held = triangle_edges(tri).groupBy("edge_id").agg(F.count("*").alias("support"))
    return edges.select("edge_id", "src", "dst").join(held, "edge_id", "left").select("edge_id", "src", "dst", F.coalesce("support", F.lit(0)).cast("bigint").alias("support"))


def _peel(edges: DataFrame, tri: DataFrame, k: int, method: str, update: str, report: IterationReport, max_rounds: int | None) -> tuple[DataFrame, DataFrame]:
    state = materialise(_counted(edges, tri), "support")
    for _ in _rounds(max_rounds):
        weak = F.col("support") < k - 2
        seen = state.agg(F.count_if(weak).alias("weak"), F.count("*").alias("edges"), F.min("support").alias("least")).first()
        report.history.append({"weak": seen["weak"], "edges": seen["edges"]})
        if not seen["weak"]:
            report.status, report.converged = "converged", True
            return state, tri
        report.rounds += 1
        gone = state.where(weak)
        if method == "ordered":
            gone = state.where(F.col("support") == seen["least"])
        elif method == "sequential":
            gone = gone.orderBy("support", "src", "dst").limit(1)
        gone = gone.select("edge_id")
        left = state.join(gone, "edge_id", "left_anti")
        if update == "recompute":
            left = materialise(left, "edges")
            tri = materialise(triangles(left), "triangles")
        else:
            for e in ("e1", "e2", "e3"):
                tri = tri.join(gone.withColumnRenamed("edge_id", e), e, "left_anti")
            tri = materialise(tri.select("e1", "e2", "e3"), "triangles")
        state = materialise(_counted(left, tri), "support")
    raise AssertionError("unreachable")


def _peel_incidence(edges: DataFrame, k: int, update: str, report: IterationReport, max_rounds: int | None) -> tuple[DataFrame, IterationReport]:
    inc = materialise(incidence(edges), "incidence")
    cells = materialise(overlap_cells(inc, inc_to_adj(inc)), "cells")
    for _ in _rounds(max_rounds):
        two = cells.groupBy(F.col("row").alias("edge_id")).agg(F.count_if(F.col("val") == 2).alias("support"))
        state = materialise(edges.join(inc.select(F.col("row").alias("edge_id")).distinct(), "edge_id", "left_semi").join(two, "edge_id", "left").select("edge_id", "src", "dst", F.coalesce("support", F.lit(0)).cast("bigint").alias("support")), "support")
        weak = F.col("support") < k - 2
        n = state.agg(F.count_if(weak).alias("weak"), F.count("*").alias("edges")).first()
        report.history.append({"weak": n["weak"], "edges": n["edges"]})
        if not n["weak"]:
            report.status, report.converged = "converged", True
            return state, report
        report.rounds += 1
        gone = state.where(weak).select(F.col("edge_id").alias("row"))
        removed = inc.join(gone, "row", "left_semi").select("row", "col", "val")
        kept = materialise(inc.join(gone, "row", "left_anti").select("row", "col", "val"), "incidence")
        if update == "incremental":
            delta = spgemm(kept, inc_to_adj(removed)).withColumn("val", -F.col("val"))
            rest = cells.join(gone, "row", "left_anti").select("row", "col", "val")
            cells = rest.unionByName(delta).groupBy("row", "col").agg(F.sum("val").alias("val")).where("val <> 0")
        else:
            cells = overlap_cells(kept, inc_to_adj(kept))
        cells, inc = materialise(cells, "cells"), kept
    raise AssertionError("unreachable")


def truss_decomposition(edges: DataFrame, *, k_start: int = 3) -> DataFrame:
    """(edge_id, src, dst, trussness): the largest k whose k-truss holds the edge; 2 for edges in no 3-truss. Each k starts
    from the supports and triangles that the last one left."""
    edges = materialise(canonical(edges), "edges")
    tri = materialise(triangles(edges), "triangles")
    state, k = edges, k_start
    out = None
    while True:
        left, tri = _peel(state, tri, k, "masked", "delta", IterationReport(), None)
        fallen = state.select("edge_id", "src", "dst").join(left.select("edge_id"), "edge_id", "left_anti").withColumn("trussness", F.lit(k - 1))
        out = fallen if out is None else out.unionByName(fallen)
        if left.isEmpty():
            break
        state, k = left.select("edge_id", "src", "dst"), k + 1
    return materialise(out, "trussness")


def check_truss(edges: DataFrame, k: int) -> bool:
    """Whether every edge has k - 2 triangles among the edges."""
    return edge_support(edges.select("edge_id", "src", "dst")).where(F.col("support") < k - 2).isEmpty()


def wasted_products(edges: DataFrame) -> DataFrame:
    """(wedges, triangles, wasted): additions of the full product against those that close a triangle."""
    deg = both_ways(edges).groupBy("row").agg(F.count("*").alias("d"))
    w = deg.agg(F.sum(F.expr("d * (d - 1) div 2")).cast("bigint").alias("wedges"))
    t = triangles(edges).agg(F.count("*").alias("triangles"))
    return w.crossJoin(t).select("wedges", "triangles", (F.col("wedges") - 3 * F.col("triangles")).alias("wasted"))
