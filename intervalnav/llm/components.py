"""Connected components by alternating stars, on the cluster and safe against hubs.

Neighbour minima come from aggregates with a map-side part and go back to the edges through joins that deal out
the edges of a hub to several tasks. Before that, tasks of bounded size may each cut their edges down to stars.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, spread_join


HELD = 1 << 16  # edges of a task that cuts them down to stars


def connected(edges: DataFrame, rounds: int = 60, held: int = 0) -> DataFrame:
    """(u, root) for every node of the edges (u, v): root is the least node of its component; roots have no row.

    With ``held`` the edges (longs) are first dealt to tasks of that many, each of which keeps one star for each of its
    components; where one task holds all edges these are the result, else the rounds go on from the stars of all tasks.
    """
    now = checkpointed(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u != v").distinct())
    if held:
        tasks = -(-now.count() // held)
        if not tasks:
            return now.select("u", F.col("v").alias("root"))
        now = checkpointed(now.repartition(tasks).mapInArrow(_stars, "u long, v long"))
        if tasks == 1:
            return now.select("u", F.col("v").alias("root"))
        now = checkpointed(now.distinct())
    mark = _mark(now)
    for _ in range(rounds):
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = checkpointed(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"), F.count("*").alias("c")))
        # Larger neighbours go to the least one.
        large = spread_join(both.where("v > u"), least, "u", "c", 2 * mark[0]).select(F.col("v").alias("u"), F.col("m").alias("v"))
        down = large.where("u != v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
        low = down.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("c"))
        small = spread_join(down, low, "u", "c", mark[0]).select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        after = checkpointed(small.where("u != v").distinct())
        before, mark, now = mark, _mark(after), after
        if mark == before:
            break
    else:
        raise RuntimeError("components did not settle")
    return now.select("u", F.col("v").alias("root"))


def _mark(edges: DataFrame) -> tuple:
    # The sum of the hashes of a set of edges, in halves so that it can't overflow.
    h = F.xxhash64("u", "v")
    return tuple(edges.agg(F.count("*"), F.sum(h.bitwiseAND(0xFFFFFFFF)), F.sum(F.shiftrightunsigned(h, 32))).first())


def _stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The least node of its component among the task's edges, for every node that is not the least."""
    above: dict[int, int] = {}

    def top(x: int) -> int:
        root = x
        while (up := above.get(root, root)) != root:
            root = up
        while x != root:
            above[x], x = root, above[x]
        return root

    for batch in batches:
        for u, v in zip(batch.column("u").to_pylist(), batch.column("v").to_pylist(), strict=True):
            a, b = top(u), top(v)
            if a != b:
                above[max(a, b)] = min(a, b)
    nodes = list(above)
    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([top(x) for x in nodes], pa.int64())], names=["u", "v"])
