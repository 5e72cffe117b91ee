"""Pruning of given candidate pools, as a join of the pools with the objects of their shard."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import kernels
from .index import _shard


def prune_pools(objects: DataFrame, pool: DataFrame, budget: int | None, witness: str = "interval", disjoint: str = "drop", shard: Column | None = None) -> DataFrame:
    """(src, dst, d, bits): one pass over the pools (src, dst); both ends must be in one shard."""
    dealt = objects.select((F.lit(0) if shard is None else shard).cast("int").alias("shard"), "id", "vec", "lo", "hi")
    own = pool.join(dealt.select(F.col("id").alias("src"), F.col("shard").alias("part")), "src").select("part", "src", "dst")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        s = _shard(left)
        at = lambda c: np.searchsorted(s.ids, right.column(c).to_numpy())
        got = kernels.prune(s, np.arange(len(s.ids)), kernels.grouped(len(s.ids), at("src"), at("dst")), budget, witness, disjoint)
        return pa.table({"src": s.ids[got.src], "dst": s.ids[got.dst], "d": got.d, "bits": got.bits.astype(np.int32)})

    return dealt.groupBy("shard").cogroup(own.groupBy("part")).applyInArrow(run, "src long, dst long, d double, bits int")
