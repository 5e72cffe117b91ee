"""A table function, so that SQL can search: SELECT * FROM interval_ann(TABLE(queries), 'index path', ef).

Its rows are queries (qid, qvec, ql, qr, k, mode); the index must be one packed Parquet folder that the workers can
open, which holds on local sessions and with a mounted store. ``index.search`` has no such limit.
"""

from __future__ import annotations

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="qid long, rank int, id long, d double")
class IntervalAnn:
    def __init__(self):
        self.shards = None

    def eval(self, row: Row, path: str, ef: int):
        import numpy as np
        import pyarrow.dataset as ds

        from ..operators.index import _load
        from ..operators.methods import IntervalGraph, Query

        if self.shards is None:
            self.shards = [_load(b) for b in ds.dataset(path).to_table(columns=["blob"]).column("blob").to_pylist()]
        query, best = Query(np.array(row["qvec"], float), row["ql"], row["qr"], row["k"], row["mode"], ef), []
        for shard, data in self.shards:
            found, _ = IntervalGraph().search(shard, data, query)
            best += [(float(np.sqrt(((shard.x[i] - query.q) ** 2).sum())), int(shard.ids[i])) for i in found]
        for rank, (d, i) in enumerate(sorted(best)[: query.k], 1):
            yield row["qid"], rank, i, d


def register(spark: SparkSession) -> None:
    spark.udtf.register("interval_ann", IntervalAnn)
