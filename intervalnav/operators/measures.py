"""Accuracy, size and effort measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def recall(found: DataFrame, truth: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, hits, n_truth, recall_k, recall_min): shares of k and of the objects that there are (null if none)."""
    hit = found.select("qid", "id").join(truth.select("qid", "id"), ["qid", "id"], "left_semi").groupBy("qid").agg(F.count("*").alias("h"))
    size = truth.groupBy("qid").agg(F.count("*").alias("n"))
    out = queries.select("qid", "k").join(hit, "qid", "left").join(size, "qid", "left")
    h, n = F.coalesce("h", F.lit(0)), F.coalesce("n", F.lit(0))
    return out.select("qid", h.cast("long").alias("hits"), n.cast("long").alias("n_truth"), (h / F.col("k")).alias("recall_k"), F.when(n > 0, h / F.least(n, F.col("k"))).alias("recall_min"))


def mean_recall(found: DataFrame, truth: DataFrame, queries: DataFrame) -> float:
    """Mean over the queries that have a valid object."""
    return recall(found, truth, queries).agg(F.avg("recall_min")).first()[0] or 0.0


def degrees(edges: DataFrame) -> DataFrame:
    """One row: edges, edges with each bit and with both, and the greatest out-degree of each."""
    per = edges.groupBy("src").agg(F.count("*").alias("n"), F.sum(F.col("bits").bitwiseAND(1)).alias("w"), F.sum(F.shiftright("bits", 1)).alias("c"))
    b = lambda x: F.sum(F.when(F.col("bits") == x, 1).otherwise(0))
    one = edges.agg(F.count("*").alias("n_edges"), (b(1) + b(3)).alias("n_within"), (b(2) + b(3)).alias("n_covers"), b(3).alias("n_both"))
    return one.crossJoin(per.agg(F.max("n").alias("max_degree"), F.max("w").alias("max_within"), F.max("c").alias("max_covers")))  # one row each


def index_bytes(edges: DataFrame, objects: DataFrame) -> DataFrame:
    """One row of logical sizes: four bytes and two bits an edge, and the entry arrays (lo, two ids, two ends) an object."""
    e, n = edges.agg(F.count("*").alias("e")), objects.agg(F.count("*").alias("n"))
    return e.crossJoin(n).select((F.col("e") * 4 + F.ceil(F.col("e") * 2 / 8)).cast("long").alias("edge_bytes"), (F.col("n") * 32).cast("long").alias("entry_bytes"))


def coverage(pool: DataFrame, edges: DataFrame) -> DataFrame:
    """One row: edges of the exact graph, and those that the pool holds."""
    held = edges.select("src", "dst").join(pool.select("src", "dst").distinct(), ["src", "dst"], "left_semi").agg(F.count("*").alias("n_held"))
    return edges.agg(F.count("*").alias("n_edges")).crossJoin(held)  # one row each


def at_recall(curve: list[tuple[float, float]], target: float) -> float | None:
    """Throughput at a recall, by straight lines between the measured (recall, throughput); None beyond them."""
    points = sorted(curve)
    for (r0, t0), (r1, t1) in zip(points, points[1:], strict=False):
        if r0 <= target <= r1:
            return t0 if r1 == r0 else t0 + (t1 - t0) * (target - r0) / (r1 - r0)
    return points[0][1] if points and target <= points[0][0] else None
