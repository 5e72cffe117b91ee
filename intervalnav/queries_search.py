"""Queries on graph searches, the baselines and the ablations.

A search with a beam of all objects on a graph that connects every valid set must give the brute-force answer,
so these have the brute-force SQL; the others have invariants.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import sqltext as st
from .operators import entry, exact, hops, index, measures
from .operators.methods import (
    Clustered,
    IntervalGraph,
    Layered,
    Lifetimes,
    Method,
    Partitioned,
    PlainGraph,
    PostFilter,
    PreFilter,
    RankTree,
    Rectangles,
    Segmented,
    Slack,
    Spanning,
    TwoHop,
)
from .plans import choose, store
from .queries_core import EXACT, MIXED_SQL, WORKLOADS, built, mixed, objects, rounded, shards_of, workload, workload_sql
from .sources import tables

QUERIES: dict = {}
SQL: dict[str, str] = {}

ALL = 1 << 20  # a beam that holds every object of a shard
BOUNDED = IntervalGraph(spatial=24, attribute=48, budget=64, rounds=3)


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def found(spark, sf_dir, method: Method, name: str, n: int, ef: int = ALL, shards: int = 1, by: str = "hash") -> DataFrame:
    packed = built(spark, sf_dir, method, WORKLOADS[name][0], shards=shards, by=by)
    return index.search(packed, workload(spark, sf_dir, name, n), ef, method)


def _truth_sql(name: str, n: int) -> str:
    return st.topk(st.PROVIDERS[WORKLOADS[name][0]], workload_sql(name, n))


# ---- searches on the interval graphs --------------------------------------------------------------------------

for _name in WORKLOADS:

    @query(f"q_search_{_name}", _truth_sql(_name, 100))
    def _search(spark, sf_dir, name=_name):
        return rounded(found(spark, sf_dir, EXACT, name, 100))


@query("q_search_mixed", st.topk(st.OBJECTS, MIXED_SQL))
def q_search_mixed(spark, sf_dir):
    return rounded(index.search(built(spark, sf_dir, EXACT), mixed(spark, sf_dir), ALL, EXACT))


@query("q_search_any", st.topk(st.OBJECTS, st.queries("any", 100)))
def q_search_any(spark, sf_dir):
    return rounded(index.search(built(spark, sf_dir, EXACT), tables.queries(spark, sf_dir, "any", 100), ALL, EXACT))


@query("q_search_hash_entry", _truth_sql("within", 100))
def q_search_hash_entry(spark, sf_dir):
    return rounded(index.search(built(spark, sf_dir, EXACT), workload(spark, sf_dir, "within", 100), ALL, replace(EXACT, entry="hash")))


@query("q_sharded_search", st.topk(st.OBJECTS, MIXED_SQL))
def q_sharded_search(spark, sf_dir):
    return rounded(index.search(built(spark, sf_dir, EXACT, shards=9, by="grid"), mixed(spark, sf_dir), ALL, EXACT))


@query("q_search_bsp", st.topk(st.OBJECTS, st.queries("covers", 12)))
def q_search_bsp(spark, sf_dir):
    o, q = objects(spark, sf_dir).select("id", "vec", "lo", "hi"), tables.queries(spark, sf_dir, "covers", 12)
    return rounded(hops.search(o, index.edges(built(spark, sf_dir, EXACT)), q, entry.lookup(q, entry.table(o)), ALL, width=256))


@query("q_reach_target", "SELECT vec_id AS qid, vec_id AS id FROM embeddings")
def q_reach_target(spark, sf_dir):
    """An object's own vector as query, a beam of one: the object is found from whatever entry."""
    o = objects(spark, sf_dir)
    q = o.select(F.col("id").alias("qid"), F.transform("vec", lambda x: x.cast("double")).alias("qvec"), (F.col("lo") - 300).alias("ql"), (F.col("hi") + 300).alias("qr"), F.lit(1).alias("k"), F.lit("within").alias("mode"))
    return index.search(built(spark, sf_dir, EXACT), q, 1, EXACT).select("qid", "id")


def _recalls(spark, sf_dir, methods: dict[str, Method], name: str, ef: int, n: int = 100, build: dict[str, Method] | None = None) -> dict[str, float]:
    q = workload(spark, sf_dir, name, n)
    truth = exact.topk(objects(spark, sf_dir, intervals=WORKLOADS[name][0]), q)
    truth, shards = store.checkpointed(truth), shards_of(spark, sf_dir)
    return {k: measures.mean_recall(index.search(built(spark, sf_dir, (build or methods)[k], WORKLOADS[name][0], shards=shards), q, ef, m), truth, q) for k, m in methods.items()}


def _one_row(spark, **values) -> DataFrame:
    return spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} boolean" for k in values))


@query("q_bounded_graph_t5", "SELECT true AS within_is_high, true AS covers_is_high")
def q_bounded_graph_t5(spark, sf_dir):
    m = {"m": IntervalGraph(spatial=32, attribute=64, budget=64, rounds=5)}
    return _one_row(spark, within_is_high=_recalls(spark, sf_dir, m, "within", 40)["m"] >= 0.95, covers_is_high=_recalls(spark, sf_dir, m, "covers", 40)["m"] >= 0.95)


@query("q_rounds_ablation", "SELECT true AS third_round_gains, true AS repair_gains")
def q_rounds_ablation(spark, sf_dir):
    small = IntervalGraph(spatial=16, attribute=32, budget=64, rounds=3)
    r = _recalls(spark, sf_dir, {"1": replace(small, rounds=1), "3": small, "none": replace(small, repair=False)}, "within", 40)
    return _one_row(spark, third_round_gains=r["3"] >= r["1"] + 0.02, repair_gains=r["3"] >= r["none"] + 0.02)


@query("q_budget_ablation", "SELECT true AS small_budget_loses, true AS attribute_pool_gains")
def q_budget_ablation(spark, sf_dir):
    base = IntervalGraph(spatial=32, attribute=64, budget=64, rounds=3)
    r = _recalls(spark, sf_dir, {"64": base, "8": replace(base, budget=8), "spatial": replace(base, spatial=96, attribute=0)}, "within", 40)
    return _one_row(spark, small_budget_loses=r["64"] >= r["8"] + 0.3, attribute_pool_gains=r["64"] >= r["spatial"] + 0.03)


@query("q_beam_recalls", " UNION ALL ".join(f"SELECT '{x}' AS workload, true AS is_high" for x in ("within", "covers", "stab", "point", "short", "long", "halves", "covers_50", "covers_500", "covers_3000")))
def q_beam_recalls(spark, sf_dir):
    """Recall of the bounded graph at a beam of 80, for every workload."""
    m = {"m": IntervalGraph(spatial=48, attribute=96, budget=128, rounds=3)}
    rows = [(x, _recalls(spark, sf_dir, m, x, 80, 200)["m"] >= 0.95) for x in ("within", "covers", "stab", "point", "short", "long", "halves", "covers_50", "covers_500", "covers_3000")]
    return spark.createDataFrame(rows, "workload string, is_high boolean")


@query("q_shards_skipped", "SELECT true AS few_are_read, true AS nothing_is_lost")
def q_shards_skipped(spark, sf_dir):
    """Short ranges on a grid of shards: a query searches those alone that can have a valid object."""
    packed, q = built(spark, sf_dir, EXACT, shards=9, by="grid"), workload(spark, sf_dir, "short", 100)
    cost = index.search(packed, q, 40, EXACT, effort=True)
    recall = measures.mean_recall(index.search(packed, q, 40, EXACT), store.checkpointed(exact.topk(objects(spark, sf_dir), q)), q)
    return _one_row(spark, few_are_read=cost.agg(F.max("shards")).first()[0] <= 4, nothing_is_lost=recall >= 0.99)


@query("q_baseline_recalls", " UNION ALL ".join(f"SELECT '{x}' AS method, true AS is_high" for x in ("hnsw", "vamana", "nsg", "hcnng", "partitioned_hnsw", "partitioned_vamana", "partitioned_nsg", "partitioned_hcnng")))
def q_baseline_recalls(spark, sf_dir):
    """Recall of the eight within methods at a beam of 60."""
    r = _recalls(spark, sf_dir, {x: BASELINES[x][0] for x in ("hnsw", "vamana", "nsg", "hcnng", "partitioned_hnsw", "partitioned_vamana", "partitioned_nsg", "partitioned_hcnng")}, "within", 60)
    return spark.createDataFrame([(x, y >= 0.9) for x, y in r.items()], "method string, is_high boolean")


@query("q_effort_against_size", "SELECT true AS grows_less_than_the_table")
def q_effort_against_size(spark, sf_dir):
    """Distances a query on the exact graph of an eighth, a half and all of the objects."""
    n, cost = objects(spark, sf_dir).count(), []
    for part in (8, 2, 1):
        packed = built(spark, sf_dir, EXACT, few=n // part)
        cost.append(index.search(packed, workload(spark, sf_dir, "covers", 100), 10, EXACT, effort=True).agg(F.avg("distances")).first()[0])
    return _one_row(spark, grows_less_than_the_table=cost[0] < cost[1] < cost[2] < 6 * cost[0])


@query("q_visited_policy", "SELECT true AS push_is_better, true AS push_is_high")
def q_visited_policy(spark, sf_dir):
    r = _recalls(spark, sf_dir, {"push": EXACT, "touch": replace(EXACT, visited="touch")}, "within", 40, build={"push": EXACT, "touch": EXACT})
    return _one_row(spark, push_is_better=r["push"] >= r["touch"], push_is_high=r["push"] >= 0.99)


@query("q_infilter_fails", "SELECT true AS plain_graph_is_lower")
def q_infilter_fails(spark, sf_dir):
    r = _recalls(spark, sf_dir, {"plain": PlainGraph(how="in"), "interval": EXACT}, "within", 40)
    return _one_row(spark, plain_graph_is_lower=r["plain"] <= r["interval"] - 0.2)


@query("q_more_neighbours_cost_more", "SELECT true AS effort_grows")
def q_more_neighbours_cost_more(spark, sf_dir):
    """Effort by k, the beam being as long as k."""
    packed, cost = built(spark, sf_dir, BOUNDED), []
    for k in (1, 5, 10, 20, 50):
        cost.append(index.search(packed, workload(spark, sf_dir, "within", 100, k), k, BOUNDED, effort=True).agg(F.sum("distances")).first()[0])
    return _one_row(spark, effort_grows=cost == sorted(cost))


@query("q_index_roundtrip", "SELECT 0::BIGINT AS nodes_differ, 0::BIGINT AS edges_differ")
def q_index_roundtrip(spark, sf_dir):
    nodes = objects(spark, sf_dir).select(store.shard_column("grid", 9).alias("shard"), "id", "vec", "lo", "hi")
    edges = index.edges(built(spark, sf_dir, EXACT, shards=9, by="grid"))
    back = store.stored(store.Index(nodes, edges))
    n = lambda a, b, name: a.exceptAll(b.select(*a.columns)).union(b.select(*a.columns).exceptAll(a)).agg(F.count("*").alias(name))
    return n(nodes.drop("vec"), back.nodes, "nodes_differ").crossJoin(n(edges, back.edges, "edges_differ"))


@query("q_routed_shards", f"""WITH o AS (SELECT *, (least(greatest(floor(lo / (10009.0 / 3)), 0), 2) * 3 + least(greatest(floor(hi / (10009.0 / 3)), 0), 2))::INTEGER AS shard FROM ({st.OBJECTS})),
  b AS (SELECT shard, min(lo) AS a, max(lo) AS b, min(hi) AS c, max(hi) AS d FROM o GROUP BY shard)
  SELECT q.qid, b.shard FROM ({MIXED_SQL}) q JOIN b ON CASE WHEN mode = 'within' THEN b.b >= ql AND c <= qr ELSE a <= ql AND d >= qr END""")
def q_routed_shards(spark, sf_dir):
    nodes = objects(spark, sf_dir).withColumn("shard", store.shard_column("grid", 9))
    return store.routed(mixed(spark, sf_dir), store.bounds(nodes)).select("qid", "shard")


@query("q_strategy", f"""SELECT qid, CASE WHEN s < 0.05 THEN 'pre' WHEN s > 0.5 THEN 'post' ELSE 'graph' END AS how FROM (
  SELECT q.qid, count(o.id) / (SELECT count(*) FROM embeddings) AS s FROM ({MIXED_SQL}) q LEFT JOIN ({st.OBJECTS}) o ON {st.VALID} GROUP BY q.qid)""")
def q_strategy(spark, sf_dir):
    return choose.strategy(exact.selectivity(objects(spark, sf_dir), mixed(spark, sf_dir)), "share").select("qid", "how")


@query("q_estimated_strategy", "SELECT true AS error_is_small")
def q_estimated_strategy(spark, sf_dir):
    o, q = objects(spark, sf_dir), mixed(spark, sf_dir)
    both = choose.estimated_share(q, choose.histogram(o)).join(exact.selectivity(o, q), "qid")
    return both.agg((F.avg(F.abs(F.col("estimate") - F.col("share"))) < 0.02).alias("error_is_small"))


# ---- baselines ------------------------------------------------------------------------------------------------

_SMALL = {"m": 12, "ef_c": 32}
#: name: (method, workload); all with a beam of everything, so they must equal brute force
BASELINES: dict[str, tuple[Method, str]] = {
    "prefilter": (PreFilter(), "within"),
    "postfilter_adaptive": (PostFilter(20, True), "within"),
    "plain_postfilter": (PlainGraph(), "within"),
    "hnsw": (Layered(**_SMALL), "within"),
    "hnsw_covers": (Layered(**_SMALL), "covers"),
    "hnsw_stab": (Layered(**_SMALL), "stab"),
    "hnsw_result_filter": (Layered(how="result", **_SMALL), "point"),
    "vamana": (Slack(**_SMALL), "within"),
    "nsg": (Spanning(**_SMALL), "within"),
    "hcnng": (Clustered(trees=6, leaf=80), "within"),
    "partitioned_hnsw": (Partitioned(Layered(**_SMALL), 80), "within"),
    "partitioned_vamana": (Partitioned(Slack(**_SMALL), 80), "within"),
    "partitioned_nsg": (Partitioned(Spanning(**_SMALL), 80), "within"),
    "partitioned_hcnng": (Partitioned(Clustered(trees=4, leaf=40), 80), "within"),
    "timestamp_graph": (Lifetimes(), "stab"),
    "segment_graph": (Rectangles(ordered=True), "point"),
    "dynamic_segment_graph": (Rectangles(), "point"),
    "range_segtree": (RankTree("edges"), "point"),
    "window_tree": (RankTree("cover"), "point"),
    "super_postfilter": (RankTree("smallest"), "point"),
    "hybrid_segments": (Segmented(), "point"),
    "range_graph": (EXACT, "point"),
}

for _name, (_method, _load) in BASELINES.items():

    @query(f"q_bl_{_name}", _truth_sql(_load, 60))
    def _baseline(spark, sf_dir, method=_method, load=_load):
        return rounded(found(spark, sf_dir, method, load, 60, shards=shards_of(spark, sf_dir)))


@query("q_bl_acorn", "SELECT true AS all_valid, true AS recall_is_high")
def q_bl_acorn(spark, sf_dir):
    m = TwoHop(m=16, gamma=4)
    q = workload(spark, sf_dir, "point", 60)
    o = objects(spark, sf_dir, intervals="point")
    got = store.checkpointed(index.search(built(spark, sf_dir, m, "point"), q, 60, m))
    bad = got.join(o.select("id", "lo", "hi"), "id").join(q.select("qid", "ql", "qr"), "qid").where("lo < ql or hi > qr").count()
    return _one_row(spark, all_valid=bad == 0, recall_is_high=measures.mean_recall(got, exact.topk(o, q), q) >= 0.9)


_POST = f"""WITH o AS MATERIALIZED ({st.OBJECTS}), q AS MATERIALIZED ({workload_sql("within", 60)}),
  c AS MATERIALIZED (SELECT qid, id, lo, hi, ql, qr, {st.sq("vec", "qvec")} AS d2 FROM q, o), n AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, id) AS r FROM c),
  f AS (SELECT qid, id, d2, row_number() OVER (PARTITION BY qid ORDER BY d2, id) AS rk FROM n WHERE r <= 100 AND lo >= ql AND hi <= qr)"""


@query("q_bl_postfilter_k100", f"{_POST} SELECT qid, rk::INTEGER AS rank, id, round(sqrt(d2), 6) AS d FROM f WHERE rk <= 10")
def q_bl_postfilter_k100(spark, sf_dir):
    return rounded(found(spark, sf_dir, PostFilter(100), "within", 60))


@query("q_recall_postfilter", f"""{_POST}, t AS (SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY d2, id) AS rk FROM c WHERE lo >= ql AND hi <= qr),
  h AS (SELECT t.qid, count(f.id) AS hits, count(*) AS n FROM (SELECT * FROM t WHERE rk <= 10) t LEFT JOIN (SELECT * FROM f WHERE rk <= 10) f USING (qid, id) GROUP BY t.qid)
  SELECT q.qid, coalesce(hits, 0) AS hits, coalesce(n, 0) AS n_truth, round(coalesce(hits, 0) / 10, 6) AS recall_k, round(hits / n, 6) AS recall_min FROM q LEFT JOIN h USING (qid)""")
def q_recall_postfilter(spark, sf_dir):
    q = workload(spark, sf_dir, "within", 60)
    r = measures.recall(found(spark, sf_dir, PostFilter(100), "within", 60), exact.topk(objects(spark, sf_dir), q), q)
    return r.select("qid", "hits", "n_truth", F.round("recall_k", 6).alias("recall_k"), F.round("recall_min", 6).alias("recall_min"))


@query("q_bl_hybrid_strategy", f"""SELECT qid, CASE WHEN s < 0.05 THEN 'pre' WHEN s > 0.5 THEN 'post' ELSE 'in' END AS how FROM (
  SELECT q.qid, count(o.id) / (SELECT count(*) FROM embeddings) AS s FROM ({st.ranges(200)}) q LEFT JOIN ({st.POINTS}) o ON lo BETWEEN ql AND qr GROUP BY q.qid)""")
def q_bl_hybrid_strategy(spark, sf_dir):
    """The strategy for each of 200 ranges; a choice by share alone, so these have no vectors and no query rows."""
    s = exact.selectivity(objects(spark, sf_dir, intervals="point"), tables.ranges(spark, 200).withColumn("mode", F.lit("within")))
    m = Segmented()
    return s.select("qid", F.when(F.col("share") < m.low, "pre").when(F.col("share") > m.high, "post").otherwise("in").alias("how"))
