"""Distances between arrays of numbers, computed in DOUBLE, and SQL functions for the session."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

ZERO = 0.0


def _sum(a: Column, b: Column, term) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: term(x.cast("double"), y.cast("double"))), F.lit(ZERO), lambda s, x: s + x)


def l2sq(a: Column, b: Column) -> Column:
    return _sum(a, b, lambda x, y: (x - y) * (x - y))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2sq(a, b))


def l1(a: Column, b: Column) -> Column:
    return _sum(a, b, lambda x, y: F.abs(x - y))


def dot(a: Column, b: Column) -> Column:
    return _sum(a, b, lambda x, y: x * y)


def cosine(a: Column, b: Column) -> Column:
    """1 less the cosine; search with it has no guarantee, since it is no metric."""
    return 1 - dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


SQL_FUNCTIONS = {
    "iv_within": "(lo DOUBLE, hi DOUBLE, ql DOUBLE, qr DOUBLE) RETURNS BOOLEAN RETURN lo >= ql AND hi <= qr",
    "iv_covers": "(lo DOUBLE, hi DOUBLE, ql DOUBLE, qr DOUBLE) RETURNS BOOLEAN RETURN lo <= ql AND hi >= qr",
    "iv_stab": "(lo DOUBLE, hi DOUBLE, t DOUBLE) RETURNS BOOLEAN RETURN t BETWEEN lo AND hi",
    "iv_hull_lo": "(a DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN least(a, b)",
    "iv_hull_hi": "(a DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN greatest(a, b)",
    "l2sq": "(a ARRAY<FLOAT>, b ARRAY<FLOAT>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (double(x) - double(y)) * (double(x) - double(y))), 0D, (s, x) -> s + x)",
}


def register(spark: SparkSession) -> None:
    """Makes the functions known to SQL; they are inlined into the plan."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
