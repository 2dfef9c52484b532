"""Arithmetic on array<double> columns, all inside Catalyst, and the SQL functions a user can register."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def norm_l1(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + F.abs(x))


def scale(a: Column, by: Column) -> Column:
    return F.transform(a, lambda x: x * by)


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def clip_l2(a: Column, bound: float) -> Column:
    """The vector, shortened to length ``bound`` if it is longer; the zero vector stays."""
    size = norm(a)
    return F.when(size <= bound, a).otherwise(scale(a, F.lit(float(bound)) / size))


def clip_l1(a: Column, bound: float) -> Column:
    size = norm_l1(a)
    return F.when(size <= bound, a).otherwise(scale(a, F.lit(float(bound)) / size))


def logsumexp(a: Column) -> Column:
    top = F.array_max(a)
    return top + F.log(F.aggregate(a, F.lit(0.0), lambda s, x: s + F.exp(x - top)))


def sigmoid(x: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-x))


# SQL text of the functions a plain ``spark.sql`` session can call
SQL_FUNCTIONS = {
    "dot": "dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "clip_l2": "clip_l2(a ARRAY<DOUBLE>, bound DOUBLE) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> x * least(1D, bound / greatest(sqrt(aggregate(a, 0D, (s, y) -> s + y * y)), 1e-300D)))",
    "logsumexp": "logsumexp(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN array_max(a) + ln(aggregate(a, 0D, (s, x) -> s + exp(x - array_max(a))))",
    "hash_uniform": "hash_uniform(k STRING) RETURNS DOUBLE RETURN CAST(conv(substr(md5(CAST(k AS BINARY)), 1, 8), 16, 10) AS BIGINT) / 4294967296D",
    "sigmoid": "sigmoid(x DOUBLE) RETURNS DOUBLE RETURN 1D / (1D + exp(-x))",
    "gaussian": "gaussian(k STRING, sigma DOUBLE) RETURNS DOUBLE RETURN sigma * sqrt(-2D * ln(1D - CAST(conv(substr(md5(CAST(concat(k, ':u') AS BINARY)), 1, 8), 16, 10) AS BIGINT) / 4294967296D)) * cos(2D * pi() * CAST(conv(substr(md5(CAST(concat(k, ':v') AS BINARY)), 1, 8), 16, 10) AS BIGINT) / 4294967296D)",
}


def register_sql_functions(spark: SparkSession) -> list[str]:
    """Create the functions for this session; returns their names."""
    for text in SQL_FUNCTIONS.values():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    return list(SQL_FUNCTIONS)
