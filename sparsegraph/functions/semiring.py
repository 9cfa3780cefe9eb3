"""Semirings as pairs of a Spark aggregate (addition) and a column expression (multiplication)."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

INF = float("inf")


@dataclass(frozen=True)
class Semiring:
    """add folds the products of a cell; mult combines two entries; zero is what absent entries mean and is never stored.

    allow_partial is false where the addition may not be combined in parts (see NonSemiring)."""

    name: str
    add: Callable[[Column], Column]
    mult: Callable[[Column, Column], Column]
    zero: object
    one: object
    scalar_add: Callable | None = None
    scalar_mult: Callable | None = None
    allow_partial: bool = True

    def check_laws(self, sample: list) -> list[str]:
        """Names of the semiring laws that fail on a sample of values; needs the scalar forms."""
        add, mul, zero, one = self.scalar_add, self.scalar_mult, self.zero, self.one
        failed = set()
        for a in sample:
            if add(a, zero) != a or add(zero, a) != a:
                failed.add("additive identity")
            if mul(a, one) != a or mul(one, a) != a:
                failed.add("multiplicative identity")
            if mul(a, zero) != zero or mul(zero, a) != zero:
                failed.add("annihilation")
            for b in sample:
                if add(a, b) != add(b, a):
                    failed.add("commutative addition")
                for c in sample:
                    if add(add(a, b), c) != add(a, add(b, c)):
                        failed.add("associative addition")
                    if mul(mul(a, b), c) != mul(a, mul(b, c)):
                        failed.add("associative multiplication")
                    if mul(a, add(b, c)) != add(mul(a, b), mul(a, c)) or mul(add(b, c), a) != add(mul(b, a), mul(c, a)):
                        failed.add("distributive")
        return sorted(failed)


def _safe_plus(a: float, b: float) -> float:
    """inf + -inf counts as the zero of the tropical semirings, which annihilates."""
    s = a + b
    return s if not math.isnan(s) else a


PLUS_TIMES = Semiring("plus_times", F.sum, lambda a, b: a * b, 0, 1, lambda a, b: a + b, lambda a, b: a * b)
MIN_PLUS = Semiring("min_plus", F.min, lambda a, b: a + b, INF, 0, min, _safe_plus)
MAX_PLUS = Semiring("max_plus", F.max, lambda a, b: a + b, -INF, 0, max, _safe_plus)
MAX_MIN = Semiring("max_min", F.max, lambda a, b: F.least(a, b), -INF, INF, max, min)
MAX_TIMES = Semiring("max_times", F.max, lambda a, b: a * b, 0, 1, max, lambda a, b: a * b)
OR_AND = Semiring("or_and", F.bool_or, lambda a, b: a & b, False, True, lambda a, b: a or b, lambda a, b: a and b)
PLUS_PAIR = Semiring("plus_pair", F.sum, lambda a, b: F.lit(1).cast("bigint"), 0, 1)
PLUS_FIRST = Semiring("plus_first", F.sum, lambda a, b: a, 0, 1)
PLUS_SECOND = Semiring("plus_second", F.sum, lambda a, b: b, 0, 1)
MIN_FIRST = Semiring("min_first", F.min, lambda a, b: a, INF, 0)
MIN_SECOND = Semiring("min_second", F.min, lambda a, b: b, INF, 0)
#: Set-valued entries: union of intersections. Absent entries mean the empty set.
UNION = Semiring("union", lambda c: F.array_sort(F.array_distinct(F.flatten(F.collect_set(c)))), lambda a, b: F.array_intersect(a, b), [], None)


def NonSemiring(name: str, add: Callable[[Column], Column], mult: Callable[[Column, Column], Column], zero: object = None) -> Semiring:
    """Any aggregate and product, unchecked. Its aggregate sees all products of a cell at once (over collected lists), so
    it needs no associativity; only the masked product keeps that affordable."""
    return Semiring(name, lambda c: add(F.sort_array(F.collect_list(c))), mult, zero, None, allow_partial=False)


ALL = {s.name: s for s in (PLUS_TIMES, MIN_PLUS, MAX_PLUS, MAX_MIN, MAX_TIMES, OR_AND, PLUS_PAIR, PLUS_FIRST, PLUS_SECOND, MIN_FIRST, MIN_SECOND)}
