"""Streams of events and objects: sessions, windows, standing queries, delta shards."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..functions import interval as iv
from ..functions.distance import l2


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, lo, hi, n): activity intervals in microseconds; batch or stream (with a watermark set before)."""
    grouped = events.groupBy("user_id", F.session_window("ts", gap).alias("w"))
    # The window ends one gap after the last event.
    end = F.unix_micros((F.col("w.end") - F.expr(f"interval {gap}")).cast("timestamp"))
    return grouped.agg(F.count("*").alias("n")).select("user_id", F.unix_micros(F.col("w.start").cast("timestamp")).alias("lo"), end.alias("hi"), "n")


def counts(events: DataFrame, width: str, slide: str | None = None, by: Column | str = "event_type") -> DataFrame:
    """(start, event_type, n): events of tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), by).agg(F.count("*").alias("n")).select(F.unix_micros(F.col("w.start").cast("timestamp")).alias("start"), "event_type", "n")


def stream(spark: SparkSession, path: str, like: DataFrame, late: str = "1 hour", time: str | None = "ts", files: int = 1) -> DataFrame:
    """A stream over Parquet files as they come, with a watermark on the time column."""
    df = spark.readStream.schema(like.schema).option("maxFilesPerTrigger", files).parquet(path)
    # Watermarks need a timestamp with a zone; a local one is read in the session's.
    return df.withColumn(time, F.col(time).cast("timestamp")).withWatermark(time, late) if time else df


def once(stream_: DataFrame, key: str) -> DataFrame:
    """The stream without repeats of a key that come within the watermark."""
    return stream_.dropDuplicatesWithinWatermark([key])


def intervals(begins: DataFrame, ends: DataFrame, key: str, longest: str = "6 hours") -> DataFrame:
    """Stream-stream join of begin and end events of one key: (key, lo, hi); both need watermarks."""
    b, e = begins.select(F.col(key).alias("k"), F.col("ts").alias("b")), ends.select(F.col(key).alias("k2"), F.col("ts").alias("e"))
    return b.join(e, (F.col("k") == F.col("k2")) & (F.col("e") >= F.col("b")) & (F.col("e") <= F.col("b") + F.expr(f"interval {longest}"))).select(F.col("k").alias(key), F.col("b").alias("lo"), F.col("e").alias("hi"))


def standing(objects: DataFrame, queries: DataFrame, state: str, checkpoint: str) -> StreamingQuery:
    """Keeps the k nearest valid objects so far of registered queries (few: they are broadcast), in a table of versions.

    Each micro-batch joins its objects with the queries, merges with the last version and writes the next one; a
    batch that is repeated after a failure writes the same version again.
    """
    spark = queries.sparkSession
    schema = "qid long, id long, d double"

    def merge(batch: DataFrame, number: int) -> None:
        hit = batch.join(F.broadcast(queries), iv.matches(F.col("mode"), F.col("lo"), F.col("hi"), F.col("ql"), F.col("qr"))).select("qid", "id", l2(F.col("vec"), F.col("qvec")).alias("d"))
        if number:
            hit = hit.union(spark.read.schema(schema).parquet(f"{state}/version={number - 1}"))
        best = hit.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy("d", "id"))).join(F.broadcast(queries.select("qid", "k")), "qid")
        best.where(F.col("r") <= F.col("k")).select("qid", "id", "d").write.mode("overwrite").parquet(f"{state}/version={number}")

    return objects.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def appended(objects: DataFrame, delta: str, checkpoint: str) -> StreamingQuery:
    """New objects into a delta table, to be searched by brute force beside the index until the next build."""

    def add(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{delta}/batch={number}")

    return objects.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def search_with_delta(packed: DataFrame, delta: DataFrame, queries: DataFrame, ef: int) -> DataFrame:
    """Index answers and those of the delta objects as one."""
    from ..operators import exact, index

    both = index.search(packed, queries, ef).select("qid", "id", "d").union(exact.topk(delta, queries).select("qid", "id", "d"))
    return exact.ranked(both, queries)
