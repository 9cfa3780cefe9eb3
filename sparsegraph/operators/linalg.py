"""Iterative matrix inversion: with kernels on DataFrames, or on the driver for small blocks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegraph.plans.iterate import IterationReport
from sparsegraph.plans.state import materialise

from .kernels import ewise_union, norm_fro, scale, spgemm, transpose

LOCAL_LIMIT = 512


def inverse_local(m: np.ndarray, *, eps: float = 1e-12, max_iter: int = 200, stop: str = "relative") -> tuple[np.ndarray, IterationReport]:
    """Newton's iteration X <- 2 X - X M X from the scaled transpose. A singular M gives the pseudo-inverse; the report's
    last residual is the largest entry of |M X - I|. stop: relative (step against X) or absolute (the step alone)."""
    m = np.asarray(m, float)
    if m.shape[0] != m.shape[1]:
        raise ValueError("only a square matrix has an inverse")
    report = IterationReport()
    r, c = np.abs(m).sum(1).max(initial=0), np.abs(m).sum(0).max(initial=0)
    if not r:
        report.status = "zero"
        return np.zeros_like(m), report
    x = m.T / (r * c)
    for k in range(max_iter):
        new = 2 * x - x @ m @ x
        step, size = np.linalg.norm(new - x), np.linalg.norm(new)
        report.rounds, x = k + 1, new
        report.history.append({"step": float(step), "residual": float(np.abs(m @ x - np.eye(len(m))).max())})
        if step <= eps * (size if stop == "relative" else 1.0):
            report.status, report.converged = "converged", True
            break
    # For a singular M the product M X is a projector short of the identity by at least 1 / n on the diagonal.
    if report.history and report.history[-1]["residual"] > 0.5 / len(m):
        report.status = "rank deficient"
    return x, report


def inverse(m: DataFrame, *, eps: float = 1e-10, max_iter: int = 100, method: str = "kernels", stop: str = "relative") -> tuple[DataFrame, IterationReport]:
    """The inverse of triples (row, col, val): with sparse kernels alone, or ("local") on the driver up to 512 keys."""
    m = materialise(m.select("row", "col", F.col("val").cast("double").alias("val")), "matrix")
    if method == "local":
        keys = [r[0] for r in m.select(F.col("row").alias("k")).union(m.select("col")).distinct().orderBy("k").limit(LOCAL_LIMIT + 1).collect()]
        if len(keys) > LOCAL_LIMIT:
            raise ValueError(f"the local inverse is for at most {LOCAL_LIMIT} keys")
        at = {k: i for i, k in enumerate(keys)}
        dense = np.zeros((len(keys), len(keys)))
        for r in m.collect():
            dense[at[r["row"]], at[r["col"]]] = r["val"]
        x, report = inverse_local(dense, eps=eps, max_iter=max_iter, stop=stop)
        rows = [(keys[i], keys[j], float(x[i, j])) for i in range(len(keys)) for j in range(len(keys)) if x[i, j]]
        return m.sparkSession.createDataFrame(rows, m.schema), report
    report = IterationReport()
    size = lambda key: m.groupBy(key).agg(F.sum(F.abs("val")).alias("s")).agg(F.max("s")).first()[0]
    r, c = size("row"), size("col")
    if not r:
        report.status = "zero"
        return m, report
    x = scale(transpose(m), 1.0 / (r * c))
    for k in range(max_iter):
        new = materialise(ewise_union(scale(x, 2.0), spgemm(spgemm(x, m), x), lambda a, b: a - b, 0.0), "inverse")
        step = norm_fro(ewise_union(new, x, lambda a, b: a - b, 0.0)).first()[0] or 0.0
        total = norm_fro(new).first()[0] or 0.0
        x, report.rounds = new, k + 1
        report.history.append({"step": step})
        if step <= eps * (total if stop == "relative" else 1.0):
            report.status, report.converged = "converged", True
            break
    eye = m.select(F.col("row").alias("k")).union(m.select("col")).distinct().select(F.col("k").alias("row"), F.col("k").alias("col"), F.lit(1.0).alias("val"))
    off = ewise_union(spgemm(m, x), eye, lambda a, b: a - b, 0.0).agg(F.max(F.abs("val"))).first()[0] or 0.0
    report.history.append({"residual": off})
    if off > 0.5 / max(eye.count(), 1):
        report.status = "rank deficient"
    return x, report


def tsqr(rows: DataFrame, k: int) -> np.ndarray:
    """R of a tall matrix (vec array<double> of length k): one small R for each batch and a tree of R's in the executors;
    the driver gets at most 32 of them."""

    def reduce(batches):
        import pyarrow as pa

        held = np.zeros((0, k))
        for batch in batches:
            x = np.asarray(batch.column(0).flatten(), float).reshape(-1, k)
            held = np.linalg.qr(np.concatenate((held, x)), mode="r")
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.list_(pa.float64()))], names=["vec"])

    part = rows.select("vec").mapInArrow(reduce, "vec array<double>")
    part = part.repartition(32).mapInArrow(reduce, "vec array<double>")
    got = np.array([r["vec"] for r in part.collect()]).reshape(-1, k)
    return np.linalg.qr(got, mode="r") if len(got) else np.zeros((k, k))
