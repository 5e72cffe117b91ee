"""Session helpers shared by the operators of this subpackage."""

from __future__ import annotations

import contextlib
import gc
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or in local runs one of our own."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        folder = "/tmp/checkpoints/intervalnav"
    return folder


BITMAP = 1 << 19  # words of 64 bits: the bound of a key filter

FREED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

_written: list[str] = []


@contextlib.contextmanager
def shuffles_freed(spark: SparkSession) -> Iterator[None]:
    """Spark deletes the shuffle files of an action begun meanwhile when it ends; a setting of running sessions.

    For actions on frames that are not run again: what follows reads the written result.
    """
    before = spark.conf.get(FREED, None)
    spark.conf.set(FREED, "true")
    try:
        yield
    finally:
        spark.conf.unset(FREED) if before is None else spark.conf.set(FREED, before)


def written(df: DataFrame, name: str) -> DataFrame:
    """The frame written once as Parquet in the shared folder and read back: lineage ends here.

    The table stays until ``release``, since frames made from it are read later.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    with shuffles_freed(spark):
        df.write.parquet(path)
    _written.append(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession, paths: list[str] | None = None) -> None:
    """Deletes tables that ``written`` has made: the given ones, or all; frames that read them are of no use after."""
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for path in list(_written if paths is None else paths):
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(conf).delete(target, True)
        if path in _written:
            _written.remove(path)


def swept(spark: SparkSession) -> None:
    """Has Spark delete checkpoints and other files of finished steps: it does so once their frames are garbage in the
    driver, which otherwise may be found half an hour later."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


@contextlib.contextmanager
def tables_made() -> Iterator[list[str]]:
    """Collects the paths of the tables that ``written`` makes meanwhile."""
    before, paths = len(_written), []
    yield paths
    paths += _written[before:]


def spread_join(left: DataFrame, right: DataFrame, key: str, count: str, total: int) -> DataFrame:
    """``left`` with the columns of ``right`` (one row a key; ``count``: the rows that left has of it, of ``total``).

    A key with more than a task's usual part of the rows is cut into as many parts as it holds of these, on both
    sides; there are at most as many such keys as partitions, and their list is broadcast.
    """
    usual = max(100, total // int(left.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    cut = right.withColumn("__cuts", F.ceil(F.col(count) / usual)).drop(count)
    heavy = F.broadcast(cut.where("__cuts > 1").select(key, "__cuts"))
    salted = left.join(heavy, key, "left").withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.coalesce("__cuts", F.lit(1)))).drop("__cuts")
    copies = cut.withColumn("__salt", F.explode(F.sequence(F.lit(0).cast("long"), F.col("__cuts") - 1))).drop("__cuts")
    return salted.join(copies, [key, "__salt"]).drop("__salt")


def marked(rows: DataFrame, key: str, wanted: DataFrame, name: str = "__marked") -> DataFrame:
    """The rows with a flag that is false only where ``key`` is not among ``wanted`` (one column); a broadcast of bounded size."""
    hashed = lambda c: F.xxhash64(c, F.lit(17))
    word = lambda c: F.pmod(hashed(c), F.lit(BITMAP)).cast("int")
    bit = lambda c: F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(hashed(c), 40).bitwiseAND(F.lit(63)).cast("int"))
    given = F.col(wanted.columns[0])
    bits = wanted.groupBy(word(given).alias("__word")).agg(F.bit_or(bit(given)).alias("__bits"))  # at most BITMAP rows
    flag = F.coalesce(F.col("__bits").bitwiseAND(bit(F.col(key))) != 0, F.lit(False))
    return rows.join(F.broadcast(bits), word(F.col(key)) == F.col("__word"), "left").select(*rows.columns, flag.alias(name))


def without(rows: DataFrame, key: str, gone: DataFrame) -> DataFrame:
    """The rows whose key is not in ``gone`` (one column, no nulls); few of the others are shuffled."""
    flagged = marked(rows, key, gone)
    unsure = flagged.where("__marked").join(gone.distinct().toDF("__gone"), F.col(key) == F.col("__gone"), "left_anti")
    return flagged.where("not __marked").union(unsure).drop("__marked")


def checkpointed(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder; its files go when the frame is garbage."""
    context = df.sparkSession.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    with shuffles_freed(df.sparkSession):
        return df.select("*").checkpoint()  # a frame made here, so that the setting holds for it


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/pages.parquet")
