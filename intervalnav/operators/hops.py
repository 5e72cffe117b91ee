"""Beam search as DataFrame rounds: all queries take a hop together. For graphs too large for one task's memory."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import interval as iv
from ..functions.distance import l2sq
from ..plans.store import checkpointed


def search(nodes: DataFrame, edges: DataFrame, queries: DataFrame, entries: DataFrame, ef: int, width: int = 4, limit: int = 10_000) -> DataFrame:
    """(qid, rank, id, d). Each round opens the ``width`` nearest unopened objects of every query's beam.

    What falls out of a full beam can never be opened later, so the state keeps the beam and the set of ids met.
    """
    q = queries.select("qid", "qvec", "ql", "qr", "mode", "k").withColumn("bit", F.when(F.col("mode") == "covers", 2).otherwise(1))
    start = entries.where("entry is not null").join(nodes.select(F.col("id").alias("entry"), "vec"), "entry").join(q, "qid")
    beam = checkpointed(start.select("qid", F.col("entry").alias("id"), l2sq(F.col("vec"), F.col("qvec")).alias("d"), F.lit(False).alias("open")))
    met = beam.select("qid", "id")
    for _ in range(limit):
        w = Window.partitionBy("qid", "open").orderBy("d", "id")
        now = beam.withColumn("r", F.row_number().over(w))
        front = now.where(~F.col("open") & (F.col("r") <= width)).select("qid", "id")
        if front.isEmpty():
            break
        step = front.join(q.select("qid", "bit"), "qid").join(edges.select(F.col("src").alias("id"), "dst", "bits"), "id").where(F.col("bits").bitwiseAND(F.col("bit")) > 0)
        fresh = step.select("qid", F.col("dst").alias("id")).distinct().join(met, ["qid", "id"], "left_anti").join(nodes.select("id", "vec", "lo", "hi"), "id").join(q, "qid")
        fresh = fresh.where(iv.matches(F.col("mode"), F.col("lo"), F.col("hi"), F.col("ql"), F.col("qr"))).select("qid", "id", l2sq(F.col("vec"), F.col("qvec")).alias("d"), F.lit(False).alias("open"))
        fresh = checkpointed(fresh)
        opened = now.withColumn("open", F.col("open") | (F.col("r") <= width)).drop("r").select("qid", "id", "d", "open")
        best = opened.union(fresh).withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy("d", "id")))
        beam = checkpointed(best.where(F.col("r") <= ef).drop("r"))
        met = checkpointed(met.union(fresh.select("qid", "id")))
    else:
        raise RuntimeError(f"the beams are not settled after {limit} rounds")
    out = beam.withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy("d", "id"))).join(q.select("qid", "k"), "qid")
    return out.where(F.col("rank") <= F.col("k")).select("qid", "rank", "id", F.sqrt("d").alias("d"))
