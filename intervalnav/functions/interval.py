"""Interval predicates as column expressions; all intervals are closed."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WITHIN, COVERS = 1, 2  # the two bits of an edge


def within(lo: Column, hi: Column, ql: Column, qr: Column) -> Column:
    return (lo >= ql) & (hi <= qr)


def covers(lo: Column, hi: Column, ql: Column, qr: Column) -> Column:
    return (lo <= ql) & (hi >= qr)


def point_within(x: Column, ql: Column, qr: Column) -> Column:
    return x.between(ql, qr)


def stab(lo: Column, hi: Column, t: Column) -> Column:
    return t.between(lo, hi)


def matches(mode: Column, lo: Column, hi: Column, ql: Column, qr: Column) -> Column:
    """By the query's mode: within, covers or any. A point query is covers with ql = qr, a scalar object has lo = hi."""
    return F.when(mode == "within", within(lo, hi, ql, qr)).when(mode == "covers", covers(lo, hi, ql, qr)).otherwise(mode == "any")


def hull(lo1: Column, hi1: Column, lo2: Column, hi2: Column) -> tuple[Column, Column]:
    return F.least(lo1, lo2), F.greatest(hi1, hi2)


def meet(lo1: Column, hi1: Column, lo2: Column, hi2: Column) -> tuple[Column, Column]:
    """The common part; it is empty where its lower end is greater."""
    return F.greatest(lo1, lo2), F.least(hi1, hi2)


def disjoint(lo1: Column, hi1: Column, lo2: Column, hi2: Column) -> Column:
    a, b = meet(lo1, hi1, lo2, hi2)
    return a > b


def witness_within(lo1: Column, hi1: Column, lo2: Column, hi2: Column, low: Column, hiw: Column) -> Column:
    """The third interval lies in the hull of the first two."""
    a, b = hull(lo1, hi1, lo2, hi2)
    return within(low, hiw, a, b)


def witness_covers(lo1: Column, hi1: Column, lo2: Column, hi2: Column, low: Column, hiw: Column) -> Column:
    """The third interval contains what the first two share, which must not be empty."""
    a, b = meet(lo1, hi1, lo2, hi2)
    return (a <= b) & covers(low, hiw, a, b)
