"""Stable scalar functions of objectives and measures, as columns and as session SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def log_sigmoid(x: Column) -> Column:
    return F.when(x >= 0, -F.log1p(F.exp(-x))).otherwise(x - F.log1p(F.exp(x)))


def log_odds(m: Column) -> Column:
    """log p - log(1 - p) for p = exp(m); null where p is 1."""
    return F.when(m < 0, m - F.when(m > -0.6931, F.log(-F.expm1(m))).otherwise(F.log1p(-F.exp(m))))


def ratio(a: Column, b: Column) -> Column:
    """a / b in double; null for b = 0."""
    return F.when(b != 0, a.cast("double") / b.cast("double"))


def mean_of(values: Column) -> Column:
    """Mean of an array of doubles; null if it is empty."""
    return F.when(F.size(values) > 0, F.aggregate(values, F.lit(0.0), lambda a, x: a + x) / F.size(values))


def sum_of(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda a, x: a + x)


def register_all(spark: SparkSession) -> None:
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION log_sigmoid(x DOUBLE) RETURNS DOUBLE RETURN CASE WHEN x >= 0 THEN -log1p(exp(-x)) ELSE x - log1p(exp(x)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION log_odds(m DOUBLE) RETURNS DOUBLE RETURN m - ln(-expm1(m))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pair_reward(ok BOOLEAN) RETURNS INT RETURN CASE WHEN ok THEN 1 ELSE -1 END")
