"""The entry table as a DataFrame: a valid object for any query in two look-ups, or proof that there is none."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def table(objects: DataFrame) -> DataFrame:
    """(pos, id, lo, hi, least_hi, least_id, greatest_hi, greatest_id) in the order of (lo, id).

    least: over this and later objects; greatest: over this and earlier ones; ties by the lesser id. Objects are dealt
    by ranges of lo; what lies beyond a range comes from one summary row for each range.
    """
    parts = int(objects.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cuts = sorted(set(objects.approxQuantile("lo", [i / parts for i in range(1, parts)], 0.01))) if parts > 1 else []
    part = F.lit(0)
    for c in cuts:
        part = part + F.when(F.col("lo") > c, 1).otherwise(0)
    up, down = F.struct(F.col("hi").alias("h"), F.col("id").alias("i")), F.struct((-F.col("hi")).alias("h"), F.col("id").alias("i"))
    dealt = objects.select("id", "lo", "hi").withColumn("p", part)
    sums = dealt.groupBy("p").agg(F.count("*").alias("n"), F.min(up).alias("up"), F.min(down).alias("down"))
    order = Window.orderBy("p")  # one row a range
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(1, Window.unboundedFollowing)
    sums = sums.select("p", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"), F.min("down").over(before).alias("down0"), F.min("up").over(after).alias("up0"))
    w = Window.partitionBy("p").orderBy("lo", "id")
    local = dealt.withColumns({
        "r": F.row_number().over(w), "up": F.min(up).over(w.rowsBetween(0, Window.unboundedFollowing)), "down": F.min(down).over(w.rowsBetween(Window.unboundedPreceding, 0)),
    })
    both = local.join(F.broadcast(sums), "p").withColumns({"u": F.least("up", "up0"), "g": F.least("down", "down0")})
    return both.select((F.col("r") + F.col("before") - 1).cast("long").alias("pos"), "id", "lo", "hi", F.col("u.h").alias("least_hi"), F.col("u.i").alias("least_id"), (-F.col("g.h")).alias("greatest_hi"), F.col("g.i").alias("greatest_id"))


def lookup(queries: DataFrame, entries: DataFrame) -> DataFrame:
    """(qid, entry): the entry object of every query, null where no object is valid.

    within: the first position with lo >= ql, covers: the last with lo <= ql; then one comparison.
    """
    e = entries.select("pos", "lo", "least_hi", "least_id", "greatest_hi", "greatest_id")
    q = queries.select("qid", "ql", "qr", "mode")
    right = e.join(F.broadcast(q.where("mode = 'within'")), F.col("lo") >= F.col("ql")).groupBy("qid", "qr").agg(F.min(F.struct("pos", "least_hi", "least_id")).alias("e"))
    left = e.join(F.broadcast(q.where("mode = 'covers'")), F.col("lo") <= F.col("ql")).groupBy("qid", "qr").agg(F.max(F.struct("pos", "greatest_hi", "greatest_id")).alias("e"))
    found = right.where("e.least_hi <= qr").select("qid", F.col("e.least_id").alias("entry")).union(left.where("e.greatest_hi >= qr").select("qid", F.col("e.greatest_id").alias("entry")))
    return q.select("qid").join(found, "qid", "left")
