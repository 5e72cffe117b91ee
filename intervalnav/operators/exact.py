"""Exact nearest neighbours under an interval predicate, by brute force over blocks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import interval as iv

QUERY_BLOCK = 4096  # queries that are broadcast at once
RESULT = "qid long, id long, d double"


def vectors(column: pa.Array, dtype=np.float64) -> np.ndarray:
    """Rows of equally long lists as a matrix."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).astype(dtype).reshape(n, -1) if n else np.zeros((0, 0), dtype)


def valid(mode: str, lo: np.ndarray, hi: np.ndarray, ql: float, qr: float) -> np.ndarray:
    if mode == "within":
        return (lo >= ql) & (hi <= qr)
    if mode == "covers":
        return (lo <= ql) & (hi >= qr)
    return np.ones(len(lo), bool)


def _blocks_of(queries: DataFrame) -> Iterator[dict]:
    """The queries in blocks that fit a broadcast, whatever their number."""
    rows, block = queries.select("qid", "qvec", "ql", "qr", "k", "mode").toLocalIterator(), []
    for row in rows:
        block.append(row)
        if len(block) == QUERY_BLOCK:
            yield block
            block = []
    if block:
        yield block


def topk(objects: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, rank, id, d): the k nearest valid objects of every query, ties by id.

    Queries are broadcast in blocks; each task keeps its own k best of a query, so k rows a query and task are shuffled.
    """
    spark = objects.sparkSession
    source = objects.select("id", "vec", "lo", "hi")
    found = None
    for block in _blocks_of(queries):
        shared = spark.sparkContext.broadcast([(r["qid"], np.array(r["qvec"], np.float64), r["ql"], r["qr"], r["k"], r["mode"]) for r in block])

        def best(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            kept: dict[int, tuple[np.ndarray, np.ndarray]] = {}
            for batch in batches:
                x = vectors(batch.column("vec"))
                ids, lo, hi = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("id", "lo", "hi"))
                for qid, v, ql, qr, k, mode in shared.value:
                    ok = np.flatnonzero(valid(mode, lo, hi, ql, qr))
                    if not len(ok):
                        continue
                    diff = x[ok] - v
                    d, i = np.einsum("ij,ij->i", diff, diff), ids[ok]
                    if qid in kept:
                        d, i = np.concatenate([d, kept[qid][0]]), np.concatenate([i, kept[qid][1]])
                    order = np.lexsort((i, d))[:k]
                    kept[qid] = d[order], i[order]
            for qid, (d, i) in kept.items():
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(d), qid)), pa.array(i), pa.array(np.sqrt(d))], names=["qid", "id", "d"])

        part = source.mapInArrow(best, RESULT)
        found = part if found is None else found.union(part)
    if found is None:
        found = spark.createDataFrame([], RESULT)
    return ranked(found, queries)


def ranked(found: DataFrame, queries: DataFrame) -> DataFrame:
    """The k best of the found rows of every query, with ranks from 1."""
    w = Window.partitionBy("qid").orderBy("d", "id")
    out = found.withColumn("rank", F.row_number().over(w))
    return out.join(queries.select("qid", "k"), "qid").where(F.col("rank") <= F.col("k")).select("qid", "rank", "id", "d")


def topk_declarative(objects: DataFrame, queries: DataFrame, distance) -> DataFrame:
    """The same as a theta join and a window, for any distance of two array columns; small inputs."""
    joined = objects.join(F.broadcast(queries), iv.matches(F.col("mode"), F.col("lo"), F.col("hi"), F.col("ql"), F.col("qr")))
    return ranked(joined.select("qid", "id", distance(F.col("vec"), F.col("qvec")).alias("d")), queries)


def selectivity(objects: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, n_valid, share) of every query, none left out."""
    total = objects.count()
    hit = objects.select("lo", "hi").join(F.broadcast(queries.select("qid", "ql", "qr", "mode")), iv.matches(F.col("mode"), F.col("lo"), F.col("hi"), F.col("ql"), F.col("qr")))
    n = hit.groupBy("qid").agg(F.count("*").alias("n"))
    return queries.select("qid").join(n, "qid", "left").select("qid", F.coalesce("n", F.lit(0)).alias("n_valid"), (F.coalesce("n", F.lit(0)) / max(total, 1)).alias("share"))


def knn_graph(objects: DataFrame, k: int, blocks: int = 4) -> DataFrame:
    """(src, dst, d): exact k nearest of every object, from block pairs; d is squared. Every vector goes to 2 * blocks groups."""
    block = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    left = objects.select("id", "vec", block.alias("a"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("b"), F.lit(0).alias("side"))
    right = objects.select("id", "vec", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("a"), block.alias("b"), F.lit(1).alias("side"))

    def pairs(table: pa.Table) -> pa.Table:
        side = table.column("side").to_numpy()
        x, ids = vectors(table.column("vec")), table.column("id").to_numpy()
        u, v, iu, iv_ = x[side == 0], x[side == 1], ids[side == 0], ids[side == 1]
        src, dst, ds = [], [], []
        for i in range(len(u)):
            diff = v - u[i]
            d = np.einsum("ij,ij->i", diff, diff)
            d[iv_ == iu[i]] = np.inf
            order = np.lexsort((iv_, d))[:k]
            order = order[np.isfinite(d[order])]
            src.append(np.full(len(order), iu[i]))
            dst.append(iv_[order])
            ds.append(d[order])
        cat = lambda parts, t: np.concatenate(parts) if parts else np.zeros(0, t)
        return pa.table({"src": cat(src, np.int64), "dst": cat(dst, np.int64), "d": cat(ds, float)})

    near = left.union(right).groupBy("a", "b").applyInArrow(pairs, "src long, dst long, d double")
    w = Window.partitionBy("src").orderBy("d", "dst")
    return near.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).drop("r")
