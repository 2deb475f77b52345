"""Vector helpers on array columns, and SQL functions that Catalyst inlines."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def axpy(alpha: Column, x: Column, y: Column) -> Column:
    return F.zip_with(x, y, lambda p, q: alpha * p + q)


def hadamard(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def one_hot(label: Column, width: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: (i == label).cast("double"))


def argmax(a: Column) -> Column:
    """Index of the largest entry, the first of equals."""
    return (F.array_position(a, F.array_max(a)) - 1).cast("int")


def register_sql_functions(spark: SparkSession) -> None:
    """sigmoid, sigmoid_prime and portable_hash as SQL expressions; no Python runs for them."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sigmoid(z DOUBLE) RETURNS DOUBLE RETURN 1 / (1 + exp(-z))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sigmoid_prime(x DOUBLE) RETURNS DOUBLE RETURN x * (1 - x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION portable_hash(a BIGINT, b BIGINT, s BIGINT) RETURNS BIGINT RETURN CAST(conv(substr(md5(concat_ws(':', a, b, s)), 1, 8), 16, 10) AS BIGINT)")
