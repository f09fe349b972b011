"""Vector expressions on array columns, in double precision on the JVM."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def let(value: Column, body) -> Column:
    """body(value) with value computed once; inside a lambda Spark would compute it for every element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def as_double(v: Column) -> Column:
    return v.cast("array<double>")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(as_double(a), as_double(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def unit(a: Column) -> Column:
    """The vector at length one; null for a zero vector."""
    return let(as_double(a), lambda v: let(norm(v), lambda size: F.when(size > 0, F.transform(v, lambda x: x / size))))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(as_double(a), as_double(b), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def unit_l2(a: Column, b: Column) -> Column:
    """Distance of the normalised vectors; null when one has no direction."""
    return l2(unit(a), unit(b))


def register(spark: SparkSession) -> None:
    """SQL functions l2_distance(a, b) and l2_normalise(a)."""
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION l2_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE "
        "RETURN sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))"
    )
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION l2_normalise(a ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> "
        "RETURN transform(a, x -> x / nullif(sqrt(aggregate(a, 0D, (s, y) -> s + y * y)), 0D))"
    )
