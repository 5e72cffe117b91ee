"""Relational operators that Spark has no form of: overlap and as-of joins, and bounded reachability."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def overlap_join(a: DataFrame, b: DataFrame, width: float) -> DataFrame:
    """(a.id, b.id) of overlapping intervals as (left_id, right_id): an equi-join on bins.

    A pair is kept in the bin where the later of the two begins, so none comes twice.
    """
    bins = lambda df, p: df.select(F.col("id").alias(f"{p}_id"), F.col("lo").alias(f"{p}_lo"), F.col("hi").alias(f"{p}_hi"), F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))).alias("bin"))
    joined = bins(a, "left").join(bins(b, "right"), "bin")
    later = F.greatest("left_lo", "right_lo")
    return joined.where((later <= F.least("left_hi", "right_hi")) & (F.floor(later / width) == F.col("bin"))).select("left_id", "right_id")


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """The left rows with the right value of the same key that is latest before the row's time, strictly; else null."""
    both = left.select(key, time, "id", F.lit(1).alias("side"), F.lit(None).cast(dict(right.dtypes)[value]).alias("v")).union(right.select(key, time, F.lit(None).cast("long").alias("id"), F.lit(0), F.col(value)))
    # Strictly before: at equal times the left row comes first.
    w = Window.partitionBy(key).orderBy(time, F.desc("side")).rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn("before", F.last("v", ignorenulls=True).over(w)).where("side = 1").select("id", key, time, F.col("before").alias(value))


def within_hops(edges: DataFrame, roots: DataFrame, hops: int) -> DataFrame:
    """(id, hop): nodes reached from the roots in at most that many hops, with the least number."""
    reached = roots.select("id", F.lit(0).alias("hop"))
    front = reached
    for hop in range(1, hops + 1):
        nxt = front.join(edges, front["id"] == edges["src"]).select(F.col("dst").alias("id")).distinct().join(reached, "id", "left_anti")
        front = nxt.select("id", F.lit(hop).alias("hop"))
        reached = reached.union(front)
    return reached
