"""Aggregation functions of fuzzy rules, over arrays of degrees and over groups.

All but ``average`` alone are used by the aligner or stand for what it is
compared with. Every one is continuous and non-decreasing in each argument,
which ``admissible`` tests numerically.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import product as cartesian

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def _sum(array: Column) -> Column:
    return F.aggregate(array, F.lit(0.0), lambda a, x: a + x)


def weakest(array: Column) -> Column:
    return F.array_min(array)


def strongest(array: Column) -> Column:
    return F.array_max(array)


def harmonic(array: Column) -> Column:
    """Harmonic mean, 0 as soon as one degree is 0."""
    inverse = F.aggregate(array, F.lit(0.0), lambda a, x: a + F.when(x > 0, 1.0 / x).otherwise(F.lit(0.0)))
    return F.when(F.array_min(array) <= 0, F.lit(0.0)).otherwise(F.size(array) / F.when(inverse > 0, inverse))


def average(array: Column) -> Column:
    return _sum(array) / F.when(F.size(array) > 0, F.size(array))


def alpha_mean(array: Column, alpha: float = 3.0) -> Column:
    """Mean times the benefit of the doubt, at most 1."""
    return F.least(F.lit(1.0), F.lit(float(alpha)) * average(array))


def product(array: Column) -> Column:
    return F.aggregate(array, F.lit(1.0), lambda a, x: a * x)


def lukasiewicz(array: Column) -> Column:
    return F.greatest(F.lit(0.0), _sum(array) - (F.size(array) - 1))


def identity(array: Column) -> Column:
    return F.element_at(array, 1)


ARRAY: dict[str, Callable[[Column], Column]] = {"min": weakest, "max": strongest, "hmean": harmonic, "mean": average, "alpha_mean": alpha_mean, "product": product, "lukasiewicz": lukasiewicz, "identity": identity}


def grouped(name: str, degree: Column, alpha: Column | float = 3.0) -> Column:
    """The same as aggregate of a group."""
    n = F.count(degree)
    if name in ("min", "identity"):
        return F.min(degree)
    if name == "max":
        return F.max(degree)
    if name == "hmean":
        return F.when(F.min(degree) <= 0, F.lit(0.0)).otherwise(n / F.sum(F.when(degree > 0, 1.0 / degree)))
    if name == "mean":
        return F.avg(degree)
    if name == "alpha_mean":
        return F.least(F.lit(1.0), (alpha if isinstance(alpha, Column) else F.lit(float(alpha))) * F.avg(degree))
    if name == "product":
        return F.when(F.min(degree) <= 0, F.lit(0.0)).otherwise(F.exp(F.sum(F.when(degree > 0, F.ln(degree)))))
    if name == "lukasiewicz":
        return F.greatest(F.lit(0.0), F.sum(degree) - (n - 1))
    raise ValueError(name)


#: The same in Python, for oracles and for solving small systems one rule at a time.
PLAIN: dict[str, Callable[[list[float]], float]] = {
    "min": min,
    "max": max,
    "identity": lambda v: v[0],
    "hmean": lambda v: 0.0 if min(v) <= 0 else len(v) / sum(1 / x for x in v),
    "mean": lambda v: sum(v) / len(v),
    "alpha_mean": lambda v, alpha=3.0: min(1.0, alpha * sum(v) / len(v)),
    "product": lambda v: __import__("math").prod(v),
    "lukasiewicz": lambda v: max(0.0, sum(v) - (len(v) - 1)),
}


def admissible(f: Callable[[list[float]], float], n: int = 2, steps: int = 20, jump: float = 0.5) -> bool:
    """Is f non-decreasing and without jumps on a grid over the unit cube?"""
    grid = [i / steps for i in range(steps + 1)]
    for point in cartesian(grid, repeat=n):
        here = f(list(point))
        if not -1e-12 <= here <= 1 + 1e-12:
            return False
        for i in range(n):
            if point[i] < 1:
                up = f([x + (1 / steps if k == i else 0) for k, x in enumerate(point)])
                if up < here - 1e-12 or up > here + jump:
                    return False
    return True


def register(spark: SparkSession) -> None:
    """SQL functions hmean, alpha_mean, cosine and rel_close for this session."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hmean(v ARRAY<DOUBLE>) RETURNS DOUBLE RETURN CASE WHEN array_min(v) <= 0 THEN 0D ELSE size(v) / aggregate(v, 0D, (a, x) -> a + CASE WHEN x > 0 THEN 1D / x ELSE 0D END) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION alpha_mean(v ARRAY<DOUBLE>, alpha DOUBLE) RETURNS DOUBLE RETURN least(1D, alpha * aggregate(v, 0D, (a, x) -> a + x) / size(v))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cosine(v ARRAY<DOUBLE>, w ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(v, w, (x, y) -> x * y), 0D, (a, x) -> a + x) / sqrt(aggregate(v, 0D, (a, x) -> a + x * x) * aggregate(w, 0D, (a, x) -> a + x * x))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rel_close(x DOUBLE, y DOUBLE, rel DOUBLE) RETURNS BOOLEAN RETURN abs(x - y) <= rel * greatest(abs(x), abs(y))")
