"""Stored layout of an index, sharding, and checkpoints in the folder that the cluster shares."""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not folder and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    return folder or "/tmp/checkpoints/intervalnav"


def checkpointed(df: DataFrame) -> DataFrame:
    context = df.sparkSession.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint()


@dataclass
class Index:
    """nodes (shard, id, vec, lo, hi) and edges (shard, src, dst, d, bits)."""

    nodes: DataFrame
    edges: DataFrame


def write(index: Index, path: str) -> None:
    """Both tables by shard, edges of a source together and the nearest first, so a shard is a run of files."""
    index.nodes.repartition("shard").sortWithinPartitions("id").write.partitionBy("shard").parquet(f"{path}/nodes")
    index.edges.repartition("shard").sortWithinPartitions("src", "d", "dst").write.partitionBy("shard").parquet(f"{path}/edges")


def read(spark: SparkSession, path: str) -> Index:
    return Index(spark.read.parquet(f"{path}/nodes"), spark.read.parquet(f"{path}/edges"))


def stored(index: Index, path: str | None = None) -> Index:
    """The index, written and read again."""
    spark = index.nodes.sparkSession
    path = path or f"{shared_folder(spark)}/index-{uuid.uuid4().hex}"
    write(index, path)
    return read(spark, path)


def shard_column(by: str, shards: int, span: float = 10009.0) -> Column:
    """Number of the shard: hash of the id, or a cell of the (lo, hi) grid, of which queries need only some."""
    if shards <= 1:
        return F.lit(0)
    if by == "hash":
        return F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int")
    if by == "grid":
        side = max(1, int(shards**0.5))
        cell = lambda c: F.least(F.greatest(F.floor(F.col(c) / (span / side)), F.lit(0)), F.lit(side - 1))
        return (cell("lo") * side + cell("hi")).cast("int")
    raise ValueError(by)


def bounds(nodes: DataFrame) -> DataFrame:
    """Least and greatest ends of every shard: one row a shard, to route queries."""
    return nodes.groupBy("shard").agg(F.min("lo").alias("lo_min"), F.max("lo").alias("lo_max"), F.min("hi").alias("hi_min"), F.max("hi").alias("hi_max"), F.count("*").alias("n"))


def routed(queries: DataFrame, shard_bounds: DataFrame) -> DataFrame:
    """(shard, query): the shards that can hold a valid object; no other has one."""
    within = (F.col("lo_max") >= F.col("ql")) & (F.col("hi_min") <= F.col("qr"))
    covers = (F.col("lo_min") <= F.col("ql")) & (F.col("hi_max") >= F.col("qr"))
    can = F.when(F.col("mode") == "within", within).when(F.col("mode") == "covers", covers).otherwise(F.lit(True))
    return queries.join(F.broadcast(shard_bounds.select("shard", "lo_min", "lo_max", "hi_min", "hi_max")), can).drop("lo_min", "lo_max", "hi_min", "hi_max")
