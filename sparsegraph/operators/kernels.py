"""Sparse kernels over triples (row, col, val) and vectors (id, val). All are lazy.

A DataFrame of triples has at most one row for each (row, col) and none whose value is the semiring's zero."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparsegraph.functions.semiring import PLUS_TIMES, Semiring

Entry = Callable[[Column], Column]


def triples(df: DataFrame, row: str, col: str, val: str | Column = "val") -> DataFrame:
    return df.select(F.col(row).alias("row"), F.col(col).alias("col"), (F.col(val) if isinstance(val, str) else val).alias("val"))


def prune(a: DataFrame, zero: object = 0) -> DataFrame:
    """Drops entries that are null, NaN or the zero."""
    kind = dict(a.dtypes)["val"]
    out = a.where(F.col("val").isNotNull())
    if kind in ("double", "float"):
        out = out.where(~F.isnan("val"))
    if isinstance(zero, list):
        return out.where(F.size("val") > 0)
    return out if zero is None else out.where(F.col("val") != F.lit(zero))


# --- products ---------------------------------------------------------------------------------------------------------


def spgemm(a: DataFrame, b: DataFrame, sr: Semiring = PLUS_TIMES, mask: DataFrame | None = None, complement: bool = False, accum: DataFrame | None = None) -> DataFrame:
    """C(i,j) = add over l of mult(A(i,l), B(l,j)). A mask drops positions before anything is summed, so the shuffle
    carries masked products alone; accum is added to the result."""
    prod = a.select("row", F.col("col").alias("_l"), F.col("val").alias("_a")).join(b.select(F.col("row").alias("_l"), "col", F.col("val").alias("_b")), "_l").select("row", "col", sr.mult(F.col("_a"), F.col("_b")).alias("val"))
    if mask is not None:
        prod = prod.join(mask.select("row", "col"), ["row", "col"], "left_anti" if complement else "left_semi")
    out = prod.groupBy("row", "col").agg(sr.add(F.col("val")).alias("val"))
    out = prune(out, sr.zero)
    return out if accum is None else ewise_add(out, accum, sr)


def gram(e: DataFrame, sr: Semiring = PLUS_TIMES, *, diagonal: bool = True, upper: bool = False) -> DataFrame:
    """E^T E as a self-join on the row, without a transpose. upper keeps row < col, decided inside the join, which halves
    the products; diagonal=False drops row = col there."""
    x, y = e.select(F.col("row").alias("_l"), F.col("col").alias("row"), F.col("val").alias("_a")), e.select(F.col("row").alias("_l"), "col", F.col("val").alias("_b"))
    both = x.join(y, "_l")
    both = both.where("row < col") if upper else both if diagonal else both.where("row <> col")
    return prune(both.select("row", "col", sr.mult(F.col("_a"), F.col("_b")).alias("val")).groupBy("row", "col").agg(sr.add(F.col("val")).alias("val")), sr.zero)


def cogram(e: DataFrame, sr: Semiring = PLUS_TIMES, **kw) -> DataFrame:
    """E E^T."""
    return gram(transpose(e), sr, **kw)


def spgemm_sym(upper: DataFrame, sr: Semiring = PLUS_TIMES) -> DataFrame:
    """The strict upper triangle of the square of the symmetric matrix whose strict upper triangle is given: one product
    for each unordered wedge."""
    return gram(symmetrize(upper), sr, upper=True)


def spmv(a: DataFrame, x: DataFrame, sr: Semiring = PLUS_TIMES) -> DataFrame:
    """y = A x."""
    prod = a.join(x.select(F.col("id").alias("col"), F.col("val").alias("_x")), "col").select(F.col("row").alias("id"), sr.mult(F.col("val"), F.col("_x")).alias("val"))
    return prune(prod.groupBy("id").agg(sr.add(F.col("val")).alias("val")), sr.zero)


def vxm(x: DataFrame, a: DataFrame, sr: Semiring = PLUS_TIMES) -> DataFrame:
    """y^T = x^T A."""
    prod = a.join(x.select(F.col("id").alias("row"), F.col("val").alias("_x")), "row").select(F.col("col").alias("id"), sr.mult(F.col("_x"), F.col("val")).alias("val"))
    return prune(prod.groupBy("id").agg(sr.add(F.col("val")).alias("val")), sr.zero)


def spmspv(a: DataFrame, x: DataFrame, sr: Semiring = PLUS_TIMES, mask: DataFrame | None = None, complement: bool = False) -> DataFrame:
    """x^T A for a sparse x: only the rows of A in x take part; a mask of ids drops results before they are summed."""
    prod = x.select(F.col("id").alias("row"), F.col("val").alias("_x")).join(a, "row").select(F.col("col").alias("id"), sr.mult(F.col("_x"), F.col("val")).alias("val"))
    if mask is not None:
        prod = prod.join(mask.select("id"), "id", "left_anti" if complement else "left_semi")
    return prune(prod.groupBy("id").agg(sr.add(F.col("val")).alias("val")), sr.zero)


def matpow(a: DataFrame, p: int, sr: Semiring = PLUS_TIMES, keep: Callable[[DataFrame], DataFrame] = lambda d: d) -> DataFrame:
    """A to the power p >= 1 by repeated squaring; keep is applied to each square (to write it, for instance)."""
    out, square = None, a
    while p:
        if p & 1:
            out = square if out is None else keep(spgemm(out, square, sr))
        p >>= 1
        if p:
            square = keep(spgemm(square, square, sr))
    return out


# --- element by element -------------------------------------------------------------------------------------------------


def ewise_mult(a: DataFrame, b: DataFrame, op: Callable[[Column, Column], Column] = lambda x, y: x * y, zero: object = 0) -> DataFrame:
    """op on the intersection of the patterns."""
    return prune(a.select("row", "col", F.col("val").alias("_a")).join(b.select("row", "col", F.col("val").alias("_b")), ["row", "col"]).select("row", "col", op(F.col("_a"), F.col("_b")).alias("val")), zero)


def ewise_add(a: DataFrame, b: DataFrame, sr: Semiring = PLUS_TIMES) -> DataFrame:
    """Union of the patterns; entries of both are added."""
    return prune(a.select("row", "col", "val").unionByName(b.select("row", "col", "val")).groupBy("row", "col").agg(sr.add(F.col("val")).alias("val")), sr.zero)


def ewise_union(a: DataFrame, b: DataFrame, op: Callable[[Column, Column], Column], zero: object = 0) -> DataFrame:
    """op on the union of the patterns, absent entries being the zero: for operations that do not commute."""
    both = a.select("row", "col", F.col("val").alias("_a")).join(b.select("row", "col", F.col("val").alias("_b")), ["row", "col"], "full_outer")
    return prune(both.select("row", "col", op(F.coalesce("_a", F.lit(zero)), F.coalesce("_b", F.lit(zero))).alias("val")), zero)


def ewise_sub(a: DataFrame, b: DataFrame) -> DataFrame:
    return ewise_union(a, b, lambda x, y: x - y)


def ewise_div(a: DataFrame, b: DataFrame) -> DataFrame:
    """a / b where both have entries; a zero divisor gives no entry."""
    return ewise_mult(a, b, lambda x, y: F.try_divide(x.cast("double"), y.cast("double")), None)


# --- parts ----------------------------------------------------------------------------------------------------------------


class Range:
    """Keys from low to high, both included."""

    def __init__(self, low, high):
        self.low, self.high = low, high


class Prefix:
    """Text keys that begin with a prefix."""

    def __init__(self, text: str):
        self.text = text


def key_filter(a: DataFrame, key: str, want, complement: bool = False) -> DataFrame:
    """Rows whose key is in a list, a Range, a Prefix or the `id` column of a DataFrame; or in none of them. Ranges and
    prefixes reach the Parquet scan."""
    if want is None:
        return a
    if isinstance(want, DataFrame):
        return a.join(want.select(F.col("id").alias(key)), key, "left_anti" if complement else "left_semi").select(*a.columns)
    c = F.col(key)
    cond = c.between(want.low, want.high) if isinstance(want, Range) else c.startswith(want.text) if isinstance(want, Prefix) else c.isin(list(want))
    return a.where(~cond if complement else cond)


def spref(a: DataFrame, rows=None, cols=None, complement_rows: bool = False, complement_cols: bool = False) -> DataFrame:
    """The sub-array at the given keys (see key_filter); all keys where none are given."""
    return key_filter(key_filter(a, "row", rows, complement_rows), "col", cols, complement_cols)


def spasgn(a: DataFrame, b: DataFrame, rows=None, cols=None, accum: Semiring | None = None) -> DataFrame:
    """A with the region rows x cols set to B (B's entries outside are ignored), or B added to it with accum."""
    inside = spref(b, rows, cols).select("row", "col", "val")
    if accum:
        return ewise_add(a, inside, accum)
    region = spref(a, rows, cols).select("row", "col")
    return a.select("row", "col", "val").join(region, ["row", "col"], "left_anti").unionByName(inside)


def select_entries(a: DataFrame, pred: Callable[[Column, Column, Column], Column]) -> DataFrame:
    return a.where(pred(F.col("row"), F.col("col"), F.col("val")))


def triu(a: DataFrame, k: int = 0) -> DataFrame:
    return a.where("row <= col" if k == 0 else "row < col") if k in (0, 1) else a.where(F.col("col") - F.col("row") >= k)


def tril(a: DataFrame, k: int = 0) -> DataFrame:
    return a.where("row >= col" if k == 0 else "row > col") if k in (0, -1) else a.where(F.col("col") - F.col("row") <= k)


def offdiag(a: DataFrame) -> DataFrame:
    return a.where("row <> col")


def diag(a: DataFrame) -> DataFrame:
    """The diagonal as a vector."""
    return a.where("row = col").select(F.col("row").alias("id"), "val")


def find(x: DataFrame, pred: Entry) -> DataFrame:
    """Ids of the entries that meet the predicate."""
    return x.where(pred(F.col("val"))).select("id")


# --- entries --------------------------------------------------------------------------------------------------------------


def apply(a: DataFrame, fn: Entry, zero: object = 0) -> DataFrame:
    return prune(a.withColumn("val", fn(F.col("val"))), zero)


def apply_indexed(a: DataFrame, fn: Callable[[Column, Column, Column], Column], zero: object = 0) -> DataFrame:
    return prune(a.withColumn("val", fn(F.col("row"), F.col("col"), F.col("val"))), zero)


def scale(a: DataFrame, s, sr: Semiring = PLUS_TIMES) -> DataFrame:
    return prune(a.withColumn("val", sr.mult(F.lit(s), F.col("val"))), sr.zero)


def scale_rows(a: DataFrame, v: DataFrame, sr: Semiring = PLUS_TIMES) -> DataFrame:
    """diag(v) A: rows without an entry in v vanish."""
    return prune(a.join(v.select(F.col("id").alias("row"), F.col("val").alias("_v")), "row").select("row", "col", sr.mult(F.col("_v"), F.col("val")).alias("val")), sr.zero)


def scale_cols(a: DataFrame, v: DataFrame, sr: Semiring = PLUS_TIMES) -> DataFrame:
    """A diag(v)."""
    return prune(a.join(v.select(F.col("id").alias("col"), F.col("val").alias("_v")), "col").select("row", "col", sr.mult(F.col("val"), F.col("_v")).alias("val")), sr.zero)


def transpose(a: DataFrame) -> DataFrame:
    return a.select(F.col("col").alias("row"), F.col("row").alias("col"), "val")


def symmetrize(a: DataFrame) -> DataFrame:
    """A + A^T of a strictly triangular A: the two have no entry in common, so nothing is summed."""
    return a.select("row", "col", "val").unionByName(transpose(a))


def identity(vertices: DataFrame) -> DataFrame:
    return vertices.select(F.col("id").alias("row"), F.col("id").alias("col"), F.lit(1).alias("val"))


def ones(vertices: DataFrame) -> DataFrame:
    return vertices.select("id", F.lit(1.0).alias("val"))


# --- folds ----------------------------------------------------------------------------------------------------------------


def reduce_rows(a: DataFrame, add: Entry = F.sum) -> DataFrame:
    return a.groupBy(F.col("row").alias("id")).agg(add(F.col("val")).alias("val"))


def reduce_cols(a: DataFrame, add: Entry = F.sum) -> DataFrame:
    return a.groupBy(F.col("col").alias("id")).agg(add(F.col("val")).alias("val"))


def reduce_all(a: DataFrame, add: Entry = F.sum) -> DataFrame:
    return a.agg(add(F.col("val")).alias("val"))


def nnz(a: DataFrame) -> int:
    return a.count()


def norm_fro(a: DataFrame) -> DataFrame:
    return a.agg(F.sqrt(F.sum(F.col("val").cast("double") * F.col("val"))).alias("val"))


def norm1(a: DataFrame) -> DataFrame:
    """Largest column sum of absolute values."""
    return reduce_cols(apply(a, F.abs, None)).agg(F.max("val").alias("val"))


def dot(x: DataFrame, y: DataFrame) -> DataFrame:
    return x.join(y.withColumnRenamed("val", "_y"), "id").agg(F.sum(F.col("val") * F.col("_y")).alias("val"))


def cosine(x: DataFrame, y: DataFrame) -> float:
    """|x.y| / (|x| |y|) over the union of the ids; 0 if either vanishes."""
    both = x.select("id", F.col("val").alias("_x")).join(y.select("id", F.col("val").alias("_y")), "id", "full_outer")
    a, b = F.coalesce("_x", F.lit(0.0)), F.coalesce("_y", F.lit(0.0))
    r = both.agg(F.sum(a * b).alias("p"), F.sum(a * a).alias("q"), F.sum(b * b).alias("s")).first()
    return abs(r["p"]) / (r["q"] * r["s"]) ** 0.5 if r["q"] and r["s"] else 0.0
