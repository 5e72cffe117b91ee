"""Queries on the relational surface around the methods: scans, joins, aggregates, windows, sets, scalars, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import sqltext as st
from .functions import interval
from .operators import exact, relational
from .plans.store import shared_folder
from .queries_core import objects
from .sources.tables import table
from .streaming import objects as streams

QUERIES: dict = {}
SQL: dict[str, str] = {}
OBJ = f"({st.OBJECTS})"


def query(name: str, sql: str):
    def add(f):
        QUERIES[name] = f
        SQL[name] = sql
        return f

    return add


def _class(length):
    return F.when(length < 2000, "short").when(length < 5000, "middle").otherwise("long")


_CLASS = "CASE WHEN hi - lo < 2000 THEN 'short' WHEN hi - lo < 5000 THEN 'middle' ELSE 'long' END"


@query("q_scan_prune", f"SELECT count(*) AS n, min(lo) AS lo_min, max(hi) AS hi_max FROM {OBJ} WHERE lo >= 2000 AND hi <= 6000")
def q_scan_prune(spark, sf_dir):
    return objects(spark, sf_dir).where((F.col("lo") >= 2000) & (F.col("hi") <= 6000)).agg(F.count("*").alias("n"), F.min("lo").alias("lo_min"), F.max("hi").alias("hi_max"))


@query("q_roundtrip_json", f"SELECT label, count(*) AS n, sum(lo) AS s FROM {OBJ} GROUP BY label")
def q_roundtrip_json(spark, sf_dir):
    import uuid

    path = f"{shared_folder(spark)}/json-{uuid.uuid4().hex}"
    objects(spark, sf_dir).select("id", "label", "lo", "hi").write.json(path)
    return spark.read.schema("id long, label int, lo double, hi double").json(path).groupBy("label").agg(F.count("*").alias("n"), F.sum("lo").alias("s"))


@query("q_filter_project", "SELECT o_orderkey, o_orderpriority, CASE WHEN o_totalprice < 5000 THEN 'low' WHEN o_totalprice < 50000 THEN 'middle' ELSE 'high' END AS class FROM orders WHERE o_totalprice BETWEEN 1000 AND 90000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus LIKE 'F%'")
def q_filter_project(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    p = F.col("o_totalprice")
    return o.where(p.between(1000, 90000) & F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_orderstatus").like("F%")).select("o_orderkey", "o_orderpriority", F.when(p < 5000, "low").when(p < 50000, "middle").otherwise("high").alias("class"))


@query("q_interval_from_dates", """SELECT o_orderkey, date_diff('day', DATE '1995-01-01', least(any_value(o_orderdate), min(l_shipdate))::DATE)::BIGINT AS lo, date_diff('day', DATE '1995-01-01', greatest(any_value(o_orderdate), max(l_shipdate))::DATE)::BIGINT AS hi
  FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey""")
def q_interval_from_dates(spark, sf_dir):
    ends = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.min("l_shipdate").alias("a"), F.max("l_shipdate").alias("b"))
    both = table(spark, sf_dir, "orders").join(ends, F.col("o_orderkey") == F.col("l_orderkey"))
    day = lambda c: F.date_diff(c.cast("date"), F.lit("1995-01-01").cast("date")).cast("long")
    return both.select("o_orderkey", day(F.least("o_orderdate", "a")).alias("lo"), day(F.greatest("o_orderdate", "b")).alias("hi"))


@query("q_math", f"SELECT id, lo + hi AS mid, hi - lo AS len, round(sqrt(hi - lo), 6) AS root, round(power((hi - lo) / 10009, 2), 6) AS share, floor(lo / 100) AS cell, abs(lo - 5000) AS off FROM {OBJ}")
def q_math(spark, sf_dir):
    n = F.col("hi") - F.col("lo")
    return objects(spark, sf_dir).select("id", (F.col("lo") + F.col("hi")).alias("mid"), n.alias("len"), F.round(F.sqrt(n), 6).alias("root"), F.round(F.pow(n / 10009, 2), 6).alias("share"), F.floor(F.col("lo") / 100).cast("double").alias("cell"), F.abs(F.col("lo") - 5000).alias("off"))


@query("q_string_tokens", "WITH w AS (SELECT lang, unnest(string_split_regex(lower(text), '[^a-z]+')) AS w FROM documents), c AS (SELECT lang, w, count(*) AS n FROM w WHERE w != '' GROUP BY ALL) SELECT lang, count(*) AS n_words, arg_min(w, (-n, w)) AS top FROM c GROUP BY lang")
def q_string_tokens(spark, sf_dir):
    w = table(spark, sf_dir, "documents").select("lang", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("w")).where("w != ''")
    return w.groupBy("lang", "w").agg(F.count("*").alias("n")).groupBy("lang").agg(F.count("*").alias("n_words"), F.min_by("w", F.struct(-F.col("n"), F.col("w"))).alias("top"))


@query("q_json_props", "SELECT event_type, round(avg((props->>'k')::INTEGER), 6) AS k, count(*) AS n FROM events GROUP BY event_type")
def q_json_props(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.avg(F.get_json_object("props", "$.k").cast("int")), 6).alias("k"), F.count("*").alias("n"))


@query("q_array_norm", "SELECT vec_id AS id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm FROM embeddings")
def q_array_norm(spark, sf_dir):
    return objects(spark, sf_dir).select("id", F.round(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")), 6).alias("norm"))


@query("q_array_topdims", "SELECT vec_id AS id, list_position(embedding, list_max(embedding))::BIGINT AS most, list_position(embedding, list_min(embedding))::BIGINT AS least FROM embeddings")
def q_array_topdims(spark, sf_dir):
    return objects(spark, sf_dir).select("id", F.array_position("vec", F.array_max("vec")).alias("most"), F.array_position("vec", F.array_min("vec")).alias("least"))


@query("q_map_agg", "SELECT label, count(*) AS n FROM embeddings GROUP BY label")
def q_map_agg(spark, sf_dir):
    per = objects(spark, sf_dir).groupBy("label").agg(F.count("*").alias("n"))
    return per.agg(F.map_from_entries(F.collect_list(F.struct("label", "n"))).alias("m")).select(F.explode("m").alias("label", "n"))


for _hint in ("broadcast", "merge", "shuffle_hash"):

    @query(f"q_join_equi_{_hint}", "SELECT c_mktsegment AS segment, count(*) AS n, round(sum(o_totalprice), 2) AS revenue FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1")
    def _equi(spark, sf_dir, hint=_hint):
        c = table(spark, sf_dir, "customer").hint(hint)
        return table(spark, sf_dir, "orders").join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("revenue"))


@query("q_join_outer", f"SELECT c_custkey, lo, hi FROM customer LEFT JOIN ({st.LIVES}) ON id = c_custkey")
def q_join_outer(spark, sf_dir):
    o = objects(spark, sf_dir, intervals="life").select("id", "lo", "hi")
    return table(spark, sf_dir, "customer").join(o, F.col("id") == F.col("c_custkey"), "left").select("c_custkey", "lo", "hi")


for _kind, _neg in (("semi", ""), ("anti", "NOT ")):

    @query(f"q_join_{_kind}", f"SELECT vec_id AS id FROM embeddings WHERE {_neg}EXISTS (SELECT 1 FROM events WHERE user_id = vec_id)")
    def _exists(spark, sf_dir, kind=_kind):
        e = table(spark, sf_dir, "events")
        return objects(spark, sf_dir).join(e, F.col("id") == F.col("user_id"), f"left_{kind}").select("id")


@query("q_join_range_overlap", f"SELECT a.id AS left_id, b.id AS right_id FROM {OBJ} a JOIN {OBJ} b ON a.lo <= b.hi AND b.lo <= a.hi")
def q_join_range_overlap(spark, sf_dir):
    o = objects(spark, sf_dir)
    return relational.overlap_join(o, o, 1000)


@query("q_join_asof", "SELECT a.o_orderkey AS id, a.o_custkey, arg_max(b.o_totalprice, b.o_orderdate) AS o_totalprice FROM orders a LEFT JOIN (SELECT o_custkey, o_orderdate, max(o_totalprice) AS o_totalprice FROM orders GROUP BY ALL) b ON b.o_custkey = a.o_custkey AND b.o_orderdate < a.o_orderdate GROUP BY ALL")
def q_join_asof(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    one = o.groupBy("o_custkey", "o_orderdate").agg(F.max("o_totalprice").alias("o_totalprice"))
    return relational.asof_join(o.withColumn("id", F.col("o_orderkey")), one, "o_custkey", "o_orderdate", "o_totalprice").select("id", "o_custkey", "o_totalprice")


_FIVE = f"WITH o AS ({st.OBJECTS}), g AS (SELECT src, dst FROM ({st.spatial_pool(5)}))"


def _five(spark, sf_dir) -> DataFrame:
    return exact.knn_graph(objects(spark, sf_dir), 5).select("src", "dst")


@query("q_two_hop", f"{_FIVE} SELECT DISTINCT a.src, b.dst FROM g a JOIN g b ON b.src = a.dst WHERE a.src != b.dst")
def q_two_hop(spark, sf_dir):
    g = _five(spark, sf_dir)
    return g.join(g.select(F.col("src").alias("dst"), F.col("dst").alias("far")), "dst").where("src != far").select("src", F.col("far").alias("dst")).distinct()


@query("q_recursive_reach", f"""WITH RECURSIVE o AS ({st.OBJECTS}), g AS (SELECT src, dst FROM ({st.spatial_pool(5)})), r(id, hop) AS (SELECT 0::BIGINT, 0 UNION SELECT dst, hop + 1 FROM r JOIN g ON src = id WHERE hop < 4)
  SELECT id, min(hop)::INTEGER AS hop FROM r GROUP BY id""")
def q_recursive_reach(spark, sf_dir):
    return relational.within_hops(_five(spark, sf_dir), spark.range(1), 4)


@query("q_agg_label_interval", f"SELECT label, count(*) AS n, round(avg(hi - lo), 6) AS len, min(lo) AS lo, max(hi) AS hi FROM {OBJ} GROUP BY label")
def q_agg_label_interval(spark, sf_dir):
    return objects(spark, sf_dir).groupBy("label").agg(F.count("*").alias("n"), F.round(F.avg(F.col("hi") - F.col("lo")), 6).alias("len"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))


@query("q_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS n FROM events GROUP BY event_type")
def q_agg_distinct(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("n"))


@query("q_bitmask_agg", f"SELECT o.id, bit_or((CASE WHEN lo >= ql AND hi <= qr THEN 1 ELSE 0 END) | (CASE WHEN lo <= ql AND hi >= qr THEN 2 ELSE 0 END))::INTEGER AS bits FROM {OBJ} o, ({st.ranges(10)}) q GROUP BY o.id")
def q_bitmask_agg(spark, sf_dir):
    from .sources.tables import ranges

    ends = [F.col(c) for c in ("lo", "hi", "ql", "qr")]
    bits = F.when(interval.within(*ends), 1).otherwise(0).bitwiseOR(F.when(interval.covers(*ends), 2).otherwise(0))
    return objects(spark, sf_dir).crossJoin(F.broadcast(ranges(spark, 10))).groupBy("id").agg(F.bit_or(bits).alias("bits"))  # ten queries


_GROUPED = "coalesce(label, -1)::INTEGER AS label, coalesce(class, 'all') AS class, count(*) AS n"
for _kind, _by in (("cube", "CUBE (label, class)"), ("rollup", "ROLLUP (label, class)"), ("grouping_sets", "GROUPING SETS ((label), (class))")):

    @query(f"q_{_kind}", f"SELECT {_GROUPED} FROM (SELECT label, {_CLASS} AS class FROM {OBJ}) GROUP BY {_by}")
    def _grouped(spark, sf_dir, kind=_kind):
        o = objects(spark, sf_dir).select("label", _class(F.col("hi") - F.col("lo")).alias("class"))
        g = o.groupingSets([["label"], ["class"]], "label", "class") if kind == "grouping_sets" else getattr(o, kind)("label", "class")
        return g.agg(F.count("*").alias("n")).select(F.coalesce("label", F.lit(-1)).alias("label"), F.coalesce("class", F.lit("all")).alias("class"), "n")


@query("q_pivot", "SELECT user_id % 7 AS g, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1")
def q_pivot(spark, sf_dir):
    p = table(spark, sf_dir, "events").groupBy((F.col("user_id") % 7).alias("g")).pivot("event_type", ["click", "view"]).count()
    return p.select("g", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view"))


_W = "(PARTITION BY label ORDER BY lo, id)"


@query("q_win_rank", f"SELECT id, row_number() OVER {_W} AS rn, rank() OVER (PARTITION BY label ORDER BY floor(lo / 1000)) AS rk, dense_rank() OVER (PARTITION BY label ORDER BY floor(lo / 1000)) AS dr, ntile(8) OVER {_W} AS nt, round(percent_rank() OVER {_W}, 6) AS pr FROM {OBJ}")
def q_win_rank(spark, sf_dir):
    w, v = Window.partitionBy("label").orderBy("lo", "id"), Window.partitionBy("label").orderBy(F.floor(F.col("lo") / 1000))
    cols = {"rn": F.row_number().over(w), "rk": F.rank().over(v), "dr": F.dense_rank().over(v), "nt": F.ntile(8).over(w)}
    return objects(spark, sf_dir).select("id", *[c.cast("long").alias(n) for n, c in cols.items()], F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("q_win_lag", f"SELECT id, lag(id) OVER (PARTITION BY label ORDER BY hi, id) AS before, lead(id) OVER (PARTITION BY label ORDER BY hi, id) AS after FROM {OBJ}")
def q_win_lag(spark, sf_dir):
    w = Window.partitionBy("label").orderBy("hi", "id")
    return objects(spark, sf_dir).select("id", F.lag("id").over(w).alias("before"), F.lead("id").over(w).alias("after"))


for _name, _f, _frame, _rows in (("suffix_min", "min", "ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING", (0, Window.unboundedFollowing)), ("prefix_max", "max", "ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW", (Window.unboundedPreceding, 0))):

    @query(f"q_win_{_name}", f"SELECT id, {_f}(hi) OVER (PARTITION BY label ORDER BY lo, id {_frame}) AS best FROM {OBJ}")
    def _frames(spark, sf_dir, f=_f, rows=_rows):
        return objects(spark, sf_dir).select("id", getattr(F, f)("hi").over(Window.partitionBy("label").orderBy("lo", "id").rowsBetween(*rows)).alias("best"))


@query("q_win_range_frame", f"SELECT id, count(*) OVER (PARTITION BY label ORDER BY lo RANGE BETWEEN 500 PRECEDING AND 500 FOLLOWING) AS n FROM {OBJ}")
def q_win_range_frame(spark, sf_dir):
    return objects(spark, sf_dir).select("id", F.count("*").over(Window.partitionBy("label").orderBy("lo").rangeBetween(-500, 500)).alias("n"))


@query("q_topk_per_group", f"SELECT label, id, rn FROM (SELECT label, id, row_number() OVER (PARTITION BY label ORDER BY hi - lo DESC, id) AS rn FROM {OBJ}) WHERE rn <= 3")
def q_topk_per_group(spark, sf_dir):
    w = Window.partitionBy("label").orderBy(F.desc(F.col("hi") - F.col("lo")), "id")
    return objects(spark, sf_dir).withColumn("rn", F.row_number().over(w).cast("long")).where("rn <= 3").select("label", "id", "rn")


@query("q_topk_global", f"SELECT id, hi - lo AS len FROM {OBJ} ORDER BY hi - lo DESC, id LIMIT 20 OFFSET 5")
def q_topk_global(spark, sf_dir):
    return objects(spark, sf_dir).select("id", (F.col("hi") - F.col("lo")).alias("len")).orderBy(F.desc("len"), "id").offset(5).limit(20)


_ONE, _TWO = f"SELECT id FROM {OBJ} WHERE lo >= 1000 AND hi <= 7000", f"SELECT id FROM {OBJ} WHERE lo <= 4000 AND hi >= 5000"
for _kind, _op in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):

    @query(f"q_set_{_kind}", f"{_ONE} {_op} {_TWO}")
    def _set(spark, sf_dir, kind=_kind):
        o = objects(spark, sf_dir)
        a, b = o.where("lo >= 1000 and hi <= 7000").select("id"), o.where("lo <= 4000 and hi >= 5000").select("id")
        return {"union": lambda: a.union(b).distinct(), "intersect": lambda: a.intersect(b), "except": lambda: a.subtract(b)}[kind]()


@query("q_hash_sample", f"SELECT id FROM {OBJ} WHERE (id * 2654435761) % 100 < 20")
def q_hash_sample(spark, sf_dir):
    return objects(spark, sf_dir).where(F.pmod(F.col("id") * 2654435761, F.lit(100)) < 20).select("id")


@query("q_sessions", """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS first FROM events),
  s AS (SELECT *, sum(first) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e) SELECT user_id, epoch_us(min(ts)) AS lo, epoch_us(max(ts)) AS hi, count(*) AS n FROM s GROUP BY user_id, s""")
def q_sessions(spark, sf_dir):
    return streams.sessions(table(spark, sf_dir, "events"))


@query("q_activity_within", "SELECT user_id, lo, hi FROM (SELECT user_id, epoch_us(min(ts)) AS lo, epoch_us(max(ts)) AS hi FROM events GROUP BY user_id) WHERE lo >= epoch_us(TIMESTAMP '2024-01-01 12:00:00') AND hi <= epoch_us(TIMESTAMP '2024-01-30 18:00:00')")
def q_activity_within(spark, sf_dir):
    us = lambda c: F.unix_micros(c.cast("timestamp"))
    life = table(spark, sf_dir, "events").groupBy("user_id").agg(us(F.min("ts")).alias("lo"), us(F.max("ts")).alias("hi"))
    at = lambda t: F.unix_micros(F.lit(t).cast("timestamp"))
    return life.where(interval.within(F.col("lo"), F.col("hi"), at("2024-01-01 12:00:00"), at("2024-01-30 18:00:00")))


@query("q_tumbling_daily", "SELECT epoch_us(date_trunc('day', ts)) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def q_tumbling_daily(spark, sf_dir):
    return streams.counts(table(spark, sf_dir, "events"), "1 day")


@query("q_sliding", "SELECT epoch_us(time_bucket(INTERVAL 6 HOUR, ts)) - k * 6 * 3600 * 1000000 AS start, event_type, count(*) AS n FROM events, range(4) r(k) GROUP BY ALL")
def q_sliding(spark, sf_dir):
    return streams.counts(table(spark, sf_dir, "events"), "1 day", "6 hours")
