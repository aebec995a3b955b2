"""Column expressions over vectors and stable scalar functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def weights(w) -> Column:
    """A driver-side vector as an array literal (small d)."""
    return F.array(*[F.lit(float(v)) for v in w])


def sigmoid(t: Column) -> Column:
    """1 / (1 + exp(-t)) without overflow."""
    e = F.exp(-F.abs(t))
    return F.when(t >= 0, 1.0 / (1.0 + e)).otherwise(e / (1.0 + e))


def softplus(t: Column) -> Column:
    """log(1 + exp(t)) without overflow."""
    return F.log1p(F.exp(-F.abs(t))) + F.greatest(t, F.lit(0.0))


def r6(x: Column) -> Column:
    """Rounded to six digits, with no negative zero."""
    return F.round(x, 6) + F.lit(0.0)


def register(spark: SparkSession) -> None:
    """SQL functions dot, sigmoid, softplus for use in spark.sql (inlined by Catalyst)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sigmoid(t DOUBLE) RETURNS DOUBLE RETURN CASE WHEN t >= 0 THEN 1 / (1 + exp(-t)) ELSE exp(t) / (1 + exp(t)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION softplus(t DOUBLE) RETURNS DOUBLE RETURN log1p(exp(-abs(t))) + greatest(t, 0D)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)")
