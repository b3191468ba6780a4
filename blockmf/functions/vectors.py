"""Vector columns (ARRAY<DOUBLE>) by higher-order functions: evaluated in the JVM, no Python."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm2(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x)


def plus(a: Column, b: Column, times: Column | float = 1.0) -> Column:
    t = times if isinstance(times, Column) else F.lit(times)
    return F.zip_with(a, b, lambda x, y: x + y * t)


def scaled(a: Column, by: Column | float) -> Column:
    t = by if isinstance(by, Column) else F.lit(by)
    return F.transform(a, lambda x: x * t)


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / F.sqrt(norm2(a) * norm2(b))


def register(spark) -> None:
    """SQL functions mf_dot(p, q), mf_norm2(p) and mf_speed_time(size, a, b): built-in expressions under names, so plans stay in the JVM."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mf_dot(p ARRAY<DOUBLE>, q ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(p, q, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mf_norm2(p ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(p, 0D, (s, x) -> s + x * x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mf_speed_time(size DOUBLE, a DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN size / (a * ln(size) + b)")
