"""Objects (id, vec, lo, hi) from the given tables, and the workloads of queries on them.

Intervals that stand for uniform ones come from integer arithmetic on the id, so that SQL can repeat them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Multipliers, offsets and moduli of the hashed end points of objects and queries.
OBJECT_ENDS = ((7919, 104729, 10007), (6101, 15013, 10009))
QUERY_ENDS = ((3571, 911, 10007), (2909, 4001, 10009))
PARTNER = (37, 11)
ASKED = 20  # rows whose id it divides are query rows
HALVES = (1500, 6000)  # widths of short and long ranges


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def hashed(key: Column, end: tuple[int, int, int]) -> Column:
    return (key * end[0] + end[1]) % end[2]


def uniform(key: Column, ends=OBJECT_ENDS) -> tuple[Column, Column]:
    a, b = (hashed(key, e).cast("double") for e in ends)
    return F.least(a, b), F.greatest(a, b)


def objects(spark: SparkSession, sf_dir: str, intervals: str = "uniform", below: int | None = None) -> DataFrame:
    """Embeddings with uniform, point or life (first to last order of the customer of that number) intervals."""
    base = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label")
    if below is not None:
        base = base.where(F.col("id") < below)
    if intervals == "life":
        life = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(*[f(F.date_diff("o_orderdate", F.lit("1995-01-01").cast("date"))).cast("double").alias(n) for f, n in ((F.min, "lo"), (F.max, "hi"))])
        return base.join(life, base["id"] == life["o_custkey"]).select("id", "vec", "label", "lo", "hi")
    if intervals == "point":
        x = hashed(F.col("id"), OBJECT_ENDS[0]).cast("double")
        return base.withColumns({"lo": x, "hi": x})
    lo, hi = uniform(F.col("id"))
    return base.withColumns({"lo": lo, "hi": hi})


def lineitem_objects(spark: SparkSession, sf_dir: str, below: int | None = None) -> DataFrame:
    """Lines as points of five features scaled to 0..1, with uniform intervals; ids are dense ranks of the lines."""
    from ..operators.candidates import dense_rank_by

    items = table(spark, sf_dir, "lineitem").withColumn("day", F.unix_micros(F.col("l_shipdate").cast("timestamp")).cast("double"))
    features = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "day"]
    bounds = F.broadcast(items.agg(*[f(c).alias(f"{n}_{c}") for c in features for f, n in ((F.min, "a"), (F.max, "b"))]))  # one row
    ranked = dense_rank_by(items, ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "day"], "id")
    if below is not None:
        ranked = ranked.where(F.col("id") < below)
    scaled = [((F.col(c) - F.col(f"a_{c}")) / F.when(F.col(f"b_{c}") > F.col(f"a_{c}"), F.col(f"b_{c}") - F.col(f"a_{c}")).otherwise(1.0)).cast("float") for c in features]
    lo, hi = uniform(F.col("id"))
    return ranked.crossJoin(bounds).select("id", F.array(*scaled).alias("vec"), lo.alias("lo"), hi.alias("hi"))


def document_objects(spark: SparkSession, sf_dir: str, dims: int = 128) -> DataFrame:
    """Documents as normalised hashed bags of words, with uniform intervals."""
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.explode(F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+")).alias("w"))
    counts = docs.groupBy("id", F.pmod(F.xxhash64("w"), F.lit(dims)).cast("int").alias("i")).agg(F.count("*").cast("double").alias("c"))
    rows = counts.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("i", "c"))).alias("m"), F.sqrt(F.sum(F.col("c") * F.col("c"))).alias("norm"))
    vec = F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: (F.coalesce(F.element_at("m", i), F.lit(0.0)) / F.col("norm")).cast("float"))
    lo, hi = uniform(F.col("id"))
    return rows.select("id", vec.alias("vec"), lo.alias("lo"), hi.alias("hi"))


def ranges(spark: SparkSession, n: int, kind: str = "uniform", width: int | None = None) -> DataFrame:
    """(qid, ql, qr) for n numbers."""
    return with_ranges(spark.range(n).withColumnRenamed("id", "qid"), kind, width)


def with_ranges(base: DataFrame, kind: str = "uniform", width: int | None = None) -> DataFrame:
    """The rows (qid) with ql and qr: uniform ranges, ranges of one width, or points (stab)."""
    if kind == "stab":
        t = hashed(F.col("qid"), QUERY_ENDS[0]).cast("double")
        return base.withColumns({"ql": t, "qr": t})
    if kind == "halves":  # every other range is short, the rest are long
        a, b, m = QUERY_ENDS[0]
        wide = F.when(F.col("qid") % 2 == 0, F.lit(HALVES[0])).otherwise(F.lit(HALVES[1]))
        low = (F.col("qid") * a + b) % (m - wide)
        return base.withColumns({"ql": low.cast("double"), "qr": (low + wide).cast("double")})
    if width is not None:
        a, b, m = QUERY_ENDS[0]
        low = hashed(F.col("qid"), (a, b, m - width)).cast("double")
        return base.withColumns({"ql": low, "qr": low + width})
    lo, hi = uniform(F.col("qid"), QUERY_ENDS)
    return base.withColumns({"ql": lo, "qr": hi})


def per_row(n: int) -> int:
    """Ranges of every query row: n queries are asked of a table of 500 objects, and in proportion of larger ones."""
    return max(1, n * ASKED // 500)


def life_ranges(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """Ranges of the lives of other customers: that of number qid * 37 + 11 among those that have one."""
    life = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(*[f(F.date_diff("o_orderdate", F.lit("1995-01-01").cast("date"))).cast("double").alias(c) for f, c in ((F.min, "ql"), (F.max, "qr"))])
    return spark.range(n).select(F.col("id").alias("qid"), (F.col("id") * PARTNER[0] + PARTNER[1]).alias("k")).join(life, F.col("k") == F.col("o_custkey")).select("qid", "ql", "qr")


def queries(spark: SparkSession, sf_dir: str, mode: str, n: int = 200, k: int = 10, kind: str = "uniform", width: int | None = None) -> DataFrame:
    """(qid, qvec, ql, qr, k, mode): every row whose id is divisible by ASKED, with ``per_row(n)`` ranges each.

    The vector is the mean of the row's and another object's.
    """
    base = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    total, per = base.count(), per_row(n)
    asked = base.where(F.col("vec_id") % ASKED == 0).select("vec_id", F.col("embedding").alias("u"), F.explode(F.sequence(F.lit(0), F.lit(per - 1))).alias("r"))
    q = with_ranges(asked.withColumn("qid", F.col("vec_id") * per + F.col("r")), kind, width).withColumn("j", (F.col("qid") * PARTNER[0] + PARTNER[1]) % total)
    both = q.join(base.select(F.col("vec_id").alias("j"), F.col("embedding").alias("v")), "j")
    mean = F.zip_with("u", "v", lambda x, y: (x.cast("double") + y.cast("double")) / 2)
    return both.select("qid", mean.alias("qvec"), "ql", "qr", F.lit(k).alias("k"), F.lit(mode).alias("mode"))


def validated(objects_: DataFrame) -> DataFrame:
    """The objects, after a check that ids are unique, ends in order, and vectors equally long and without NaN."""
    bad = objects_.agg(
        F.count("*").alias("n"), F.count_distinct("id").alias("ids"), F.count_distinct(F.size("vec")).alias("dims"),
        F.sum(F.when(F.col("id").isNull() | F.col("vec").isNull() | F.col("lo").isNull() | F.col("hi").isNull() | (F.col("lo") > F.col("hi")) | F.isnan("lo") | F.isnan("hi") | F.exists("vec", lambda x: x.isNull() | F.isnan(x)), 1).otherwise(0)).alias("bad"),
    ).first()
    if bad["n"] and (bad["bad"] or bad["ids"] != bad["n"] or bad["dims"] != 1):
        raise ValueError(f"objects are not valid: {bad.asDict()}")
    return objects_
