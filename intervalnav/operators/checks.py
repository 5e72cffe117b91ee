"""The theory's properties as queries that count violations."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import index, kernels
from .methods import IntervalGraph


def filtered(objects: DataFrame, mode: str, ql: float, qr: float) -> DataFrame:
    if mode == "within":
        return objects.where((F.col("lo") >= ql) & (F.col("hi") <= qr))
    return objects.where((F.col("lo") <= ql) & (F.col("hi") >= qr))


def induced(edges: DataFrame, objects: DataFrame, bit: int) -> DataFrame:
    """(src, dst) of the active edges between the given objects."""
    own = objects.select("id")
    active = edges.where(F.col("bits").bitwiseAND(bit) > 0).select("src", "dst")
    return active.join(own.withColumnRenamed("id", "src"), "src", "left_semi").join(own.withColumnRenamed("id", "dst"), "dst", "left_semi")


def heredity(objects: DataFrame, mode: str, ql: float, qr: float, method: IntervalGraph) -> DataFrame:
    """One row: edges of the graph built on the valid objects, and how many only it or only the induced graph has."""
    bit = kernels.COVERS if mode == "covers" else kernels.WITHIN
    some = filtered(objects, mode, ql, qr)
    own = induced(index.edges(index.build(some, method)), some, bit)
    cut = induced(index.edges(index.build(objects, method)), some, bit)
    n = lambda df, name: df.agg(F.count("*").alias(name))
    return n(own, "n_own").crossJoin(n(own.exceptAll(cut), "only_own")).crossJoin(n(cut.exceptAll(own), "only_induced"))  # one row each


def monotone_violations(packed: DataFrame, bit: int, overlapping_only: bool = False) -> DataFrame:
    """(src, dst) of the pairs where no active edge of the source leads strictly nearer to the target."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for blob in batch.column("blob").to_pylist():
                s, data = index._load(blob)
                n = len(s.ids)
                graph = kernels.Adjacency.of(n, data["src"], data["dst"], data["bits"])
                out_s, out_d = [], []
                for u in range(n):
                    span = slice(graph.begin[u], graph.begin[u + 1])
                    near = graph.dst[span][graph.bits[span] & bit > 0]
                    own = s.sq(np.full(n, u), np.arange(n))
                    best = np.stack([s.sq(np.full(n, w), np.arange(n)) for w in near]).min(0) if len(near) else np.full(n, np.inf)
                    bad = (best >= own) & (np.arange(n) != u) & (own > 0)
                    if overlapping_only:
                        bad &= (np.maximum(s.lo[u], s.lo) <= np.minimum(s.hi[u], s.hi))
                    out_d.append(s.ids[bad])
                    out_s.append(np.full(int(bad.sum()), s.ids[u]))
                cat = lambda p: np.concatenate(p) if p else np.zeros(0, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(cat(out_s)), pa.array(cat(out_d))], names=["src", "dst"])

    return packed.select("blob").mapInArrow(run, "src long, dst long")


def definition_violations(edges: DataFrame, objects: DataFrame) -> DataFrame:
    """(src, dst, bit) of edges whose set bit has a witness: a strictly nearer neighbour with the bit between the two."""
    from ..functions import interval as iv
    from ..functions.distance import l2sq

    o = objects.select("id", "vec", "lo", "hi")
    u, v, w = (o.toDF(*(f"{p}_{c}" for c in ("id", "vec", "lo", "hi"))) for p in "uvw")
    one, two = edges.select("src", "dst", "d", "bits"), edges.select("src", F.col("dst").alias("mid"), F.col("d").alias("md"), F.col("bits").alias("mbits"))
    near = one.join(two, "src").where("md < d").where(F.col("bits").bitwiseAND(F.col("mbits")) > 0)
    near = near.join(u, F.col("src") == F.col("u_id")).join(v, F.col("dst") == F.col("v_id")).join(w, F.col("mid") == F.col("w_id")).where(l2sq(F.col("v_vec"), F.col("w_vec")) < F.col("d"))
    c = {n: F.col(n) for n in near.columns}
    args = (c["u_lo"], c["u_hi"], c["v_lo"], c["v_hi"], c["w_lo"], c["w_hi"])
    both = c["bits"].bitwiseAND(c["mbits"])
    bad = F.when((both.bitwiseAND(1) > 0) & iv.witness_within(*args), 1).when((both.bitwiseAND(2) > 0) & iv.witness_covers(*args), 2)
    return near.withColumn("bit", bad).where("bit is not null").select("src", "dst", "bit").distinct()
