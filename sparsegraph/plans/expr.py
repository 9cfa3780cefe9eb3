"""A lazy tree of matrix expressions that is rewritten before it becomes DataFrames.

PySpark cannot add rules to the optimiser, so algebraic rewrites live here: transposes fold into the choice of join keys,
E^T E becomes a self-join, an element-wise product with a pattern becomes a mask below the sum, sums over rows of a product
become two vector products, products of patterns count instead of multiplying, triangle and diagonal selections move into
the join."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparsegraph.functions.semiring import PLUS_PAIR, PLUS_TIMES, Semiring
from sparsegraph.operators import kernels as K


class Expr:
    """Operators: @ product, + sum, * element-wise product, .T transpose, triu(k), offdiag(), row_sums(), apply(fn)."""

    pattern = False

    @property
    def T(self) -> Expr:
        return Transpose(self)

    def __matmul__(self, other: Expr) -> Expr:
        return Product(self, other)

    def __add__(self, other: Expr) -> Expr:
        return Sum(self, other)

    def __mul__(self, other: Expr) -> Expr:
        return Times(self, other)

    def triu(self, k: int = 1) -> Expr:
        return Select(self, "upper" if k else "upper0")

    def offdiag(self) -> Expr:
        return Select(self, "offdiag")

    def apply(self, fn: Callable[[Column], Column]) -> Expr:
        return Apply(self, fn)

    def row_sums(self) -> Expr:
        return RowSums(self)

    def rewrite(self) -> Expr:
        return self

    def plan(self) -> DataFrame:
        raise NotImplementedError

    def lower(self) -> DataFrame:
        return self.rewrite().plan()


@dataclass
class Leaf(Expr):
    """Triples; pattern says that every value is 1."""

    df: DataFrame
    pattern: bool = False

    def plan(self) -> DataFrame:
        return self.df


@dataclass
class Transpose(Expr):
    of: Expr

    def rewrite(self) -> Expr:
        x = self.of.rewrite()
        if isinstance(x, Transpose):
            return x.of
        if isinstance(x, Product):  # (A B)^T = B^T A^T, of which the transposes fold into join keys
            return Product(Transpose(x.b), Transpose(x.a), x.sr, x.mask and Transpose(x.mask)).rewrite()
        if isinstance(x, Sum):
            return Sum(Transpose(x.a), Transpose(x.b)).rewrite()
        return Transpose(x)

    @property
    def pattern(self) -> bool:
        return self.of.pattern

    def plan(self) -> DataFrame:
        return K.transpose(self.of.plan())


@dataclass
class Product(Expr):
    a: Expr
    b: Expr
    sr: Semiring = PLUS_TIMES
    mask: Expr | None = None
    select: str | None = None

    def rewrite(self) -> Expr:
        a, b = self.a.rewrite(), self.b.rewrite()
        sr = PLUS_PAIR if self.sr is PLUS_TIMES and a.pattern and b.pattern else self.sr
        return Product(a, b, sr, self.mask.rewrite() if self.mask else None, self.select)

    def is_gram(self) -> bool:
        return isinstance(self.a, Transpose) and self.a.of is self.b or isinstance(self.a, Transpose) and isinstance(self.a.of, Leaf) and isinstance(self.b, Leaf) and self.a.of.df is self.b.df

    def plan(self) -> DataFrame:
        if self.is_gram() and self.mask is None:
            return K.gram(self.b.plan(), self.sr, upper=self.select == "upper", diagonal=self.select != "offdiag") if self.select != "upper0" else K.triu(K.gram(self.b.plan(), self.sr))
        out = K.spgemm(self.a.plan(), self.b.plan(), self.sr, self.mask.plan() if self.mask else None)
        return select(out, self.select)


def select(df: DataFrame, how: str | None) -> DataFrame:
    return {None: lambda d: d, "upper": lambda d: K.triu(d, 1), "upper0": K.triu, "offdiag": K.offdiag}[how](df)


@dataclass
class Sum(Expr):
    a: Expr
    b: Expr

    def rewrite(self) -> Expr:
        return Sum(self.a.rewrite(), self.b.rewrite())

    def plan(self) -> DataFrame:
        return K.ewise_add(self.a.plan(), self.b.plan())


@dataclass
class Times(Expr):
    a: Expr
    b: Expr

    def rewrite(self) -> Expr:
        a, b = self.a.rewrite(), self.b.rewrite()
        for x, y in ((a, b), (b, a)):
            if isinstance(x, Product) and x.mask is None and x.select is None and y.pattern and x.sr.allow_partial:
                return Product(x.a, x.b, x.sr, y)
        return Times(a, b)

    @property
    def pattern(self) -> bool:
        return self.a.pattern and self.b.pattern

    def plan(self) -> DataFrame:
        return K.ewise_mult(self.a.plan(), self.b.plan())


@dataclass
class Select(Expr):
    of: Expr
    how: str

    def rewrite(self) -> Expr:
        x = self.of.rewrite()
        if isinstance(x, Product) and x.select is None:
            return Product(x.a, x.b, x.sr, x.mask, self.how)
        return Select(x, self.how)

    @property
    def pattern(self) -> bool:
        return self.of.pattern

    def plan(self) -> DataFrame:
        return select(self.of.plan(), self.how)


@dataclass
class Apply(Expr):
    of: Expr
    fn: Callable[[Column], Column]

    def rewrite(self) -> Expr:
        x = self.of.rewrite()
        if isinstance(x, Apply):
            f, g = self.fn, x.fn
            return Apply(x.of, lambda c: f(g(c)))
        return Apply(x, self.fn)

    def plan(self) -> DataFrame:
        return K.apply(self.of.plan(), self.fn)


@dataclass
class RowSums(Expr):
    of: Expr

    def rewrite(self) -> Expr:
        return RowSums(self.of.rewrite())

    def plan(self) -> DataFrame:
        x = self.of
        if isinstance(x, Product) and x.mask is None and x.select is None and x.sr in (PLUS_TIMES, PLUS_PAIR):
            # (A B) 1 = A (B 1): the product is never formed. An Apply between the two would forbid it.
            inner = K.reduce_rows(x.b.plan())
            return K.spmv(x.a.plan(), inner)
        return K.reduce_rows(x.plan(), F.sum)
