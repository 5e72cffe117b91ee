"""Choice of a strategy for each query from estimated selectivity."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def histogram(objects: DataFrame, cells: int = 32) -> DataFrame:
    """(a, b, n, ...): objects in a grid of lower and upper ends, with the grid's bounds; at most cells * cells rows."""
    bounds = F.broadcast(objects.agg(F.min("lo").alias("x0"), F.max("hi").alias("x1")))  # one row
    width = F.when(F.col("x1") > F.col("x0"), (F.col("x1") - F.col("x0")) / cells).otherwise(F.lit(1.0))
    cell = lambda c: F.least(F.floor((F.col(c) - F.col("x0")) / F.col("width")), F.lit(cells - 1)).cast("int")
    return objects.select("lo", "hi").crossJoin(bounds).withColumn("width", width).groupBy(cell("lo").alias("a"), cell("hi").alias("b"), "x0", "width").agg(F.count("*").alias("n"))


def estimated_share(queries: DataFrame, grid: DataFrame) -> DataFrame:
    """(qid, estimate): valid share, each cell counted by the part of it that the range takes in, ends being independent."""
    total = grid.agg(F.sum("n").alias("total"))
    part = lambda cell, x: F.least(F.greatest((F.col(x) - F.col("x0")) / F.col("width") - F.col(cell), F.lit(0.0)), F.lit(1.0))
    joined = F.broadcast(grid).crossJoin(queries.select("qid", "ql", "qr", "mode"))  # a grid of fixed size
    within = (1 - part("a", "ql")) * part("b", "qr")
    covers = part("a", "ql") * (1 - part("b", "qr"))
    share = F.when(F.col("mode") == "within", within).when(F.col("mode") == "covers", covers).otherwise(F.lit(1.0))
    return joined.groupBy("qid").agg(F.sum(share * F.col("n")).alias("s")).crossJoin(F.broadcast(total)).select("qid", (F.col("s") / F.col("total")).alias("estimate"))


def strategy(shares: DataFrame, share: str = "estimate", low: float = 0.05, high: float = 0.5) -> DataFrame:
    """With how: pre (compare all valid), graph, or post (search, then filter)."""
    return shares.withColumn("how", F.when(F.col(share) < low, "pre").when(F.col(share) > high, "post").otherwise("graph"))
