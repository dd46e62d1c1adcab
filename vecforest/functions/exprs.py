"""Vector, bound and code expressions out of built-in functions."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def _sum(xs: Column) -> Column:
    return F.aggregate(xs, F.lit(0.0), lambda a, x: a + x)


def doubles(v: Column | str) -> Column:
    return F.col(v).cast("array<double>") if isinstance(v, str) else v.cast("array<double>")


def dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: x * y))


def l2sq(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2sq(a, b))


def l1(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: F.abs(x - y)))


def linf(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x - y)), F.lit(0.0), lambda m, x: F.greatest(m, x))


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """0 where a vector is zero."""
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n).otherwise(F.lit(0.0))


def normalise(a: Column) -> Column:
    """A zero vector stays."""
    n = norm(a)
    return F.when(n > 0, F.transform(a, lambda x: x / n)).otherwise(a)


def scale(a: Column, by: float) -> Column:
    return F.transform(a, lambda x: x * by)


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def lower_bound(q: Column, lo: Column, hi: Column, K: int) -> Column:
    """Least distance of a point to a box; unrolled, so that it compiles into the stage."""
    gaps = [F.greatest(F.element_at(lo, j) - F.element_at(q, j), F.element_at(q, j) - F.element_at(hi, j), F.lit(0.0)) for j in range(1, K + 1)]
    return F.sqrt(reduce(lambda a, b: a + b, [g * g for g in gaps]))


def upper_bound(q: Column, lo: Column, hi: Column, K: int) -> Column:
    """Greatest distance of a point to a box."""
    far = [F.greatest(F.abs(F.element_at(q, j) - F.element_at(lo, j)), F.abs(F.element_at(q, j) - F.element_at(hi, j))) for j in range(1, K + 1)]
    return F.sqrt(reduce(lambda a, b: a + b, [g * g for g in far]))


def box_gap(alo: Column, ahi: Column, blo: Column, bhi: Column, K: int) -> Column:
    """Least distance of two boxes."""
    gaps = [F.greatest(F.element_at(alo, j) - F.element_at(bhi, j), F.element_at(blo, j) - F.element_at(ahi, j), F.lit(0.0)) for j in range(1, K + 1)]
    return F.sqrt(reduce(lambda a, b: a + b, [g * g for g in gaps]))


def symbol_native(x: Column, interior: Column) -> Column:
    """Symbol by counting the interior edges that are at most x."""
    return F.size(F.filter(interior, lambda e: e <= x))


def symbol_halving(x: Column, interior: Column, bits: int) -> Column:
    """Symbol by halving the regions `bits` times; interior holds 2 ** bits - 1 edges."""
    at = F.lit(0)
    for b in range(bits - 1, -1, -1):
        at = F.when(x >= F.element_at(interior, at + (1 << b)), at + (1 << b)).otherwise(at)
    return at


def root_key(code: Column, K: int, bits: int = 8) -> Column:
    """The K leading bits of a code, first dimension in the highest place."""
    return reduce(lambda a, b: a + b, [F.shiftright(F.element_at(code, j + 1).cast("long"), bits - 1) * (1 << (K - 1 - j)) for j in range(K)])


def register(spark: SparkSession) -> None:
    """SQL functions over arrays of doubles."""
    s = spark.sql
    s("CREATE OR REPLACE TEMPORARY FUNCTION vf_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (m, x) -> m + x)")
    s("CREATE OR REPLACE TEMPORARY FUNCTION vf_l2sq(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (m, x) -> m + x)")
    s("CREATE OR REPLACE TEMPORARY FUNCTION vf_l2(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (m, x) -> m + x))")
