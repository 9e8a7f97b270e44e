"""Dominance between cost vectors, as Spark expressions.

Vectors come as arrays of longs, or (faster, wholly in generated code) as lists of columns of known width.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def weakly_dominates(a: Column, b: Column) -> Column:
    """a is nowhere worse than b."""
    return F.forall(F.zip_with(a, b, lambda x, y: x <= y), lambda z: z)


def same_cost(a: Column, b: Column) -> Column:
    return a == b


def dominates(a: Column, b: Column) -> Column:
    """a is nowhere worse than b and somewhere better."""
    return weakly_dominates(a, b) & F.exists(F.zip_with(a, b, lambda x, y: x < y), lambda z: z)


def set_dominates(members: Column, b: Column) -> Column:
    """Some member of an array of vectors dominates b."""
    return F.exists(members, lambda a: dominates(a, b))


def wide_weakly_dominates(a: list[Column], b: list[Column]) -> Column:
    return reduce(lambda p, q: p & q, (x <= y for x, y in zip(a, b, strict=True)))


def wide_dominates(a: list[Column], b: list[Column]) -> Column:
    """The same over columns: comparisons only, no arrays."""
    return wide_weakly_dominates(a, b) & reduce(lambda p, q: p | q, (x < y for x, y in zip(a, b, strict=True)))


def vec_max(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.greatest(x, y))


def vec_min(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.least(x, y))


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0).cast("long"), lambda s, x: s + x)


def compare_costs(a: Column, b: Column) -> Column:
    """'better', 'worse', 'equal' or 'incomparable', seen from a."""
    return F.when(same_cost(a, b), "equal").when(weakly_dominates(a, b), "better").when(weakly_dominates(b, a), "worse").otherwise("incomparable")


def global_bound(before: Column, cost: Column, after: Column, whole: Column) -> Column:
    """Least cost of any s-t path through a subpath: bounds before and after it added, and never below the bound of s-t."""
    return vec_max(vec_add(vec_add(before, cost), after), whole)


def weighted_total(costs: Column, weights: list[float]) -> Column:
    """Single combined cost; positive weights always pick a member of the front."""
    if min(weights) <= 0:
        raise ValueError("weights must be positive")
    terms = F.zip_with(costs, F.array(*map(F.lit, weights)), lambda x, w: x * w)
    return F.aggregate(terms, F.lit(0).cast("double"), lambda s, x: s + x)


#: SQL-defined functions; the analyzer inlines them.
SQL_FUNCTIONS = (
    "CREATE OR REPLACE TEMPORARY FUNCTION weakly_dominates(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS BOOLEAN RETURN forall(zip_with(a, b, (x, y) -> x <= y), z -> z)",
    "CREATE OR REPLACE TEMPORARY FUNCTION dominates(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS BOOLEAN RETURN forall(zip_with(a, b, (x, y) -> x <= y), z -> z) AND exists(zip_with(a, b, (x, y) -> x < y), z -> z)",
)


def register_sql(spark) -> None:
    for text in SQL_FUNCTIONS:
        spark.sql(text)
