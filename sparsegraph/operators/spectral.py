"""Leading eigenpairs, PCA and SVD of triples or of dense vectors, by block iterations; centring stays implicit."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegraph.plans.state import materialise, remove

from .nmf import fits, gram_factor, names, project, start_value


def rotate(f: DataFrame, m: np.ndarray) -> DataFrame:
    """F M for rows (id, w0..) and a small M."""
    k = m.shape[0]
    return f.select("id", *[sum(F.lit(float(m[s, t])) * F.col(f"w{s}") for s in range(k)).alias(f"w{t}") for t in range(m.shape[1])])


def orthonormal(f: DataFrame, k: int) -> DataFrame:
    """Rows with the same column space and orthonormal columns, from the k x k Gram matrix."""
    f = materialise(f, "block")
    v, u = np.linalg.eigh(gram_factor(f, k))
    keep = np.maximum(v, max(v.max(initial=0), 1e-300) * 1e-14)
    return rotate(f, u @ np.diag(keep**-0.5))


def svd(a: DataFrame, k: int, *, iters: int = 8, extra: int = 4, seed: int = 1, method: str = "subspace") -> tuple[DataFrame, np.ndarray, DataFrame]:
    """(U, singular values, V): rows (id, w0..) by row key, and by column key, of triples (row, col, val). subspace iterates
    a block; lanczos grows a basis of k + 2 extra + iters single vectors, one product with A^T A each. A matrix of lower
    rank gives fewer than k with lanczos."""
    a = materialise(a.select("row", "col", F.col("val").cast("double").alias("val")), "matrix")
    if method == "lanczos":
        return _svd_lanczos(a, k, k + 2 * extra + iters, seed)
    if method != "subspace":
        raise ValueError(method)
    p = k + extra
    ids = a.select(F.col("col").alias("id")).distinct()
    h = F.pmod(F.xxhash64("id"), F.lit(1 << 31))
    v = orthonormal(ids.select("id", *[(start_value(h, t, seed) - 0.5).alias(f"w{t}") for t in range(p)]), p)
    for _ in range(iters):
        u = orthonormal(project(a, v, p, "col"), p)
        v = orthonormal(project(a, u, p, "row"), p)
    b = materialise(project(a, v, p, "col"), "block")  # A V
    values, rot = np.linalg.eigh(gram_factor(b, p))
    order = np.argsort(values)[::-1][:k]
    s = np.sqrt(np.maximum(values[order], 0))
    return rotate(b, rot[:, order] / np.maximum(s, 1e-300)), s, rotate(v, rot[:, order])


def _svd_lanczos(a: DataFrame, k: int, steps: int, seed: int) -> tuple[DataFrame, np.ndarray, DataFrame]:
    """Every step reads the matrix twice, so it is written twice: by row and by column, with numbers for keys. A vector that
    can be broadcast meets the copy sorted by the key of the result, whose sums combine before the shuffle; the matrix
    stays where it is. For a longer vector the matrix is shuffled."""
    keys, n = {}, {}
    for side in ("row", "col"):
        ids = a.select(F.col(side).alias("id")).distinct()
        code = F.col("id") if dict(ids.dtypes)["id"] in ("int", "bigint") else F.monotonically_increasing_id()
        keys[side] = materialise(ids.withColumn("code", code), "keys")
        n[side] = keys[side].count()
    coded = a
    for side in ("row", "col"):
        if a.schema[side].dataType != keys[side].schema["code"].dataType:
            coded = coded.join(keys[side].select(F.col("id").alias(side), F.col("code").alias(f"_{side}")), side).drop(side).withColumnRenamed(f"_{side}", side)
    coded = coded.select("row", "col", "val")
    sorted_by = {s: materialise(coded.repartition(s).sortWithinPartitions(s), f"by-{s}") for s in ("row", "col")}

    def onto(x: DataFrame, width: int, by: str) -> DataFrame:
        if fits(n[by], width, "bigint"):
            return project(sorted_by["col" if by == "row" else "row"], F.broadcast(x), width, by)
        return project(sorted_by[by], x, width, by)

    # The start follows from the keys themselves, not from their codes.
    h = F.pmod(F.xxhash64("id"), F.lit(1 << 31))
    start = keys["col"].select(F.col("code").alias("id"), (start_value(h, 0, seed) - 0.5).alias("w0"))
    values, v = lanczos(lambda x: onto(onto(x, 1, "col"), 1, "row"), start, k, steps=steps)
    s = np.sqrt(np.maximum(values, 0))
    u = rotate(onto(v, len(s), "col"), np.diag(1 / np.maximum(s, 1e-300)))
    named = lambda f, side: f.withColumnRenamed("id", "code").join(keys[side], "code").select("id", *names(len(s)))
    return named(u, "row"), s, named(v, "col")


def lanczos(product: Callable[[DataFrame], DataFrame], start: DataFrame, k: int, *, steps: int) -> tuple[np.ndarray, DataFrame]:
    """(the k largest eigenvalues, vectors (id, w0..)) of a symmetric operator on rows (id, w0), from a start vector. The basis
    is one table with a column for each step; a new vector is made orthogonal to all of it twice. Ends early where nothing
    new is left."""
    first = start.select("id", "w0")
    size = float(first.agg(F.sqrt(F.sum(F.col("w0") * F.col("w0")))).first()[0] or 0.0)
    if not size:
        return np.zeros(0), first.select("id")
    basis = first.select("id", (F.col("w0") / F.lit(size)).alias("w0"))
    t = np.zeros((steps, steps))
    used, last = steps, None
    for j in range(steps):
        image = product(basis.select("id", F.col(f"w{j}").alias("w0"))).select("id", F.col("w0").alias("x"))
        # The basis with its newest vector, beside the image of that: written once a step.
        both = materialise(basis.join(image, "id", "left").withColumn("x", F.coalesce("x", F.lit(0.0))), "image")
        if last is not None:
            remove(last)
        last, basis = both, both.drop("x")
        for _ in range(2):
            r = both.agg(F.sum(F.col("x") * F.col("x")).alias("square"), *[F.sum(F.col("x") * F.col(n)).alias(n) for n in names(j + 1)]).first()
            t[j, j] += r[f"w{j}"]
            both = both.withColumn("x", F.col("x") - sum(F.lit(float(r[n])) * F.col(n) for n in names(j + 1)))
        # What the second pass took off is of the size of rounding errors.
        size = max(r["square"] - sum(r[n] ** 2 for n in names(j + 1)), 0.0) ** 0.5
        if j + 1 == steps or size <= 1e-12 * max(abs(t[j, j]), t[0, 0], 1e-300):
            used = j + 1
            break
        t[j, j + 1] = t[j + 1, j] = size
        basis = both.select("id", *names(j + 1), (F.col("x") / F.lit(size)).alias(f"w{j + 1}"))
    values, rot = np.linalg.eigh(t[:used, :used])
    order = np.argsort(values)[::-1][:k]
    return values[order], rotate(basis, rot[:, order])


def top_eigs(a: DataFrame, k: int, **kw) -> tuple[np.ndarray, DataFrame]:
    """The k eigenvalues largest in size of a symmetric matrix, and their vectors."""
    _, _, v = svd(a, k, **kw)
    v = materialise(v, "vectors")
    av = project(a, v, k, "col")
    r = v.join(av.select("id", *[F.col(n).alias(f"b{n}") for n in names(k)]), "id").agg(*[F.sum(F.col(n) * F.col(f"b{n}")).alias(n) for n in names(k)]).first()
    return np.array([r[n] or 0.0 for n in names(k)]), v


def covariance(rows: DataFrame, d: int) -> tuple[np.ndarray, np.ndarray, int]:
    """(mean, covariance, count) of dense vectors (vec): partial sums of outer products in the executors, one d x d block
    for each task, summed before it comes to the driver."""

    def part(batches):
        import pyarrow as pa

        n, s, q = 0, np.zeros(d), np.zeros((d, d))
        for batch in batches:
            x = np.asarray(batch.column(0).flatten(), float).reshape(-1, d)
            n, s, q = n + len(x), s + x.sum(0), q + x.T @ x
        flat = np.concatenate(([n], s, q.reshape(-1)))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat)), pa.int64()), pa.array(flat)], names=["at", "v"])

    sums = rows.select(F.col("vec").cast("array<double>").alias("vec")).where(F.size("vec") == d).mapInArrow(part, "at bigint, v double").groupBy("at").agg(F.sum("v").alias("v")).collect()
    flat = np.zeros(1 + d + d * d)
    for r in sums:
        flat[r["at"]] = r["v"]
    n = int(flat[0])
    mean = flat[1 : d + 1] / max(n, 1)
    return mean, flat[d + 1 :].reshape(d, d) / max(n, 1) - np.outer(mean, mean), n


def pca(rows: DataFrame, k: int, d: int) -> tuple[DataFrame, np.ndarray, np.ndarray]:
    """(component, explained, loadings), eigenvalues and the d x k basis of dense vectors (vec) of length d <= 4096."""
    if d > 4096:
        raise ValueError("dense principal components are for at most 4096 dimensions; use svd on triples")
    mean, cov, n = covariance(rows, d)
    values, vectors = np.linalg.eigh(cov)
    order = np.argsort(values)[::-1][:k]
    basis = vectors[:, order] * np.sign(vectors[np.abs(vectors[:, order]).argmax(0), order])
    total = max(float(values.sum()), 1e-300)
    out = [(i, float(values[o] / total), [float(x) for x in basis[:, i]]) for i, o in enumerate(order)]
    return rows.sparkSession.createDataFrame(out, "component int, explained double, loadings array<double>"), values[order], basis
