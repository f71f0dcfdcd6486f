"""Vector functions as column expressions, and fixed-point similarities.

Similarities are BIGINT micro-units (the inner product times a million, rounded), so that bounds,
sums and comparisons are exact and independent of the order of addition.
"""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

MICRO = 1_000_000


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def sim6(a: Column, b: Column) -> Column:
    return F.round(dot(a, b) * MICRO).cast("bigint")


def l2sq(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2sq(a, b))


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def normalize(a: Column) -> Column:
    """A zero vector stays as it is. `a` and its norm are bound once a row: a lambda would find both again for each element."""
    scaled = lambda b: F.when(b["n"] > 0, F.transform(b["v"], lambda x: x / b["n"])).otherwise(b["v"])
    both = F.transform(F.array(a), lambda v: F.struct(v.alias("v"), norm(v).alias("n")))
    return F.transform(both, scaled)[0]


def vadd(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vscale(a: Column, by: Column) -> Column:
    return F.transform(a, lambda x: x * by)


def argmax(a: Column) -> Column:
    """The first place of the largest element, from 0; -1 for an empty array."""
    return F.when(F.size(a) == 0, -1).otherwise(F.array_position(a, F.array_max(a)).cast("int") - 1)


def micro(tau: float) -> int:
    return round(tau * MICRO)


def register(spark: SparkSession) -> None:
    """vec_dot and vec_sim6 as SQL functions, which Catalyst inlines."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), CAST(0 AS DOUBLE), (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_sim6(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS BIGINT RETURN CAST(round(aggregate(zip_with(a, b, (x, y) -> x * y), CAST(0 AS DOUBLE), (s, x) -> s + x) * 1000000) AS BIGINT)")
