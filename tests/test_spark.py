"""Spark operators: catalogue samples against SQL, streams, sources, plans."""

import math
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    return c


def rows(found, columns):
    key = lambda v: f"{v:.5g}" if isinstance(v, float) and not math.isnan(v) else str(v)
    order = sorted(columns)
    return sorted(tuple(key(r[columns.index(c)]) for c in order) for r in found)


SAMPLE = [
    "q_pred_within", "q_pred_mixed", "q_exact_within", "q_exact_stab", "q_attr_candidates", "q_entry_table", "q_entry_within", "q_search_mixed", "q_bl_hnsw", "q_bl_timestamp_graph",
    "q_bl_window_tree", "q_recall_postfilter", "q_join_range_overlap", "q_sessions", "q_cube", "q_win_range_frame", "q_sharded_search",
]


@pytest.mark.parametrize("name", SAMPLE)
def test_catalogue(spark, con, name):
    from intervalnav import catalog

    df = catalog.QUERIES[name](spark, DATA)
    want = con.execute(catalog.SQL[name])
    columns = [d[0] for d in want.description]
    assert rows([tuple(r) for r in df.collect()], df.columns) == rows(want.fetchall(), columns)


def test_entry_and_contract(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


def test_filters_reach_the_scan(spark):
    df = spark.read.parquet(f"{DATA}/orders.parquet").where("o_totalprice between 10 and 1000").select("o_orderkey")
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(o_totalprice)" in plan and "o_comment" not in plan


def test_inverted_range_is_rejected(spark):
    from intervalnav import queries_core as qc
    from intervalnav.operators import index

    q = qc.workload(spark, DATA, "within", 3).withColumns({"ql": F.lit(5.0), "qr": F.lit(1.0)})
    with pytest.raises(Exception, match="inverted"):
        index.search(qc.built(spark, DATA, qc.EXACT), q, 10, qc.EXACT).collect()


def test_bad_objects_are_rejected(spark):
    from intervalnav.sources.tables import validated

    make = lambda rows_: spark.createDataFrame(rows_, "id long, vec array<float>, lo double, hi double")
    assert validated(make([(1, [0.0], 0.0, 1.0), (2, [1.0], 1.0, 1.0)])).count() == 2
    assert validated(make([])).count() == 0
    for bad in [(1, [0.0], 2.0, 1.0), (1, None, 0.0, 1.0), (1, [float("nan")], 0.0, 1.0), (2, [0.0], 0.0, 1.0), (1, [0.0, 1.0], 0.0, 1.0)]:
        with pytest.raises(ValueError):
            validated(make([(2, [0.0], 0.0, 1.0), bad]))


def test_dense_ranks_over_ties(spark):
    from intervalnav.operators.candidates import dense_rank_by

    df = spark.createDataFrame([(i, float(i % 3)) for i in range(50)], "id long, v double")
    got = {r["id"]: r["pos"] for r in dense_rank_by(df, ["v", "id"], "pos").collect()}
    assert got == {i: n for n, i in enumerate(sorted(range(50), key=lambda i: (i % 3, i)))}


def test_vector_files(spark, tmp_path):
    from intervalnav.sources.vectorfiles import VectorFiles

    x = np.arange(30, dtype="<f4").reshape(10, 3)
    path = str(tmp_path / "x.fvecs")
    np.concatenate([np.full((10, 1), 3, "<i4"), x.view("<i4")], 1).astype("<i4").tofile(path)
    spark.dataSource.register(VectorFiles)
    got = spark.read.format("vectors").option("kind", "fvecs").option("records", 4).load(path).orderBy("id").collect()
    assert [r["vec"] for r in got] == x.tolist() and [r["id"] for r in got] == list(range(10))


def test_table_function(spark, tmp_path):
    from intervalnav import queries_core as qc
    from intervalnav.functions import tablefunc
    from intervalnav.operators import index

    path = str(tmp_path / "packed")
    qc.built(spark, DATA, qc.EXACT).write.parquet(path)
    tablefunc.register(spark)
    q = qc.workload(spark, DATA, "within", 20)
    q.createOrReplaceTempView("few_queries")
    got = spark.sql(f"SELECT * FROM interval_ann(TABLE(few_queries), '{path}', 1000)")
    want = index.search(qc.built(spark, DATA, qc.EXACT), q, 1000, qc.EXACT)
    assert sorted((r["qid"], r["rank"], r["id"]) for r in got.collect()) == sorted((r["qid"], r["rank"], r["id"]) for r in want.collect())


def test_hop_search_and_descent_agree_with_kernels(spark):
    from intervalnav import queries_core as qc
    from intervalnav.operators import entry, exact, hops, index

    o, q = qc.objects(spark, DATA).select("id", "vec", "lo", "hi"), qc.workload(spark, DATA, "within", 4)
    got = hops.search(o, index.edges(qc.built(spark, DATA, qc.EXACT)), q, entry.lookup(q, entry.table(o)), 1000, width=300)
    want = exact.topk(o, q)
    assert {(r["qid"], r["rank"], r["id"]) for r in got.collect()} == {(r["qid"], r["rank"], r["id"]) for r in want.collect()}


def write_in_parts(df, path, n):
    for i, part in enumerate(df.randomSplit([1.0] * n, 3)):
        part.coalesce(1).write.mode("append").parquet(path)
    return path


def test_standing_queries_end_at_the_batch_answer(spark, tmp_path):
    from intervalnav import queries_core as qc
    from intervalnav.operators import exact
    from intervalnav.streaming import objects as st

    o = qc.objects(spark, DATA).select("id", "vec", "lo", "hi")
    q = qc.workload(spark, DATA, "within", 15).persist()
    path = write_in_parts(o, str(tmp_path / "in"), 3)
    run = st.standing(st.stream(spark, path, o, time=None), q, str(tmp_path / "state"), str(tmp_path / "cp"))
    run.awaitTermination()
    last = max(int(d.split("=")[1]) for d in os.listdir(tmp_path / "state"))
    got = spark.read.parquet(str(tmp_path / "state" / f"version={last}"))
    want = exact.topk(o, q)
    assert {(r["qid"], r["id"]) for r in got.collect()} == {(r["qid"], r["id"]) for r in want.collect()}


def test_delta_is_searched_beside_the_index(spark, tmp_path):
    from intervalnav import queries_core as qc
    from intervalnav.operators import exact, index
    from intervalnav.streaming import objects as st

    o, q = qc.objects(spark, DATA).select("id", "vec", "lo", "hi"), qc.workload(spark, DATA, "covers", 15)
    packed = index.build(o.where("id < 400"), qc.EXACT)
    path = write_in_parts(o.where("id >= 400"), str(tmp_path / "in"), 2)
    st.appended(st.stream(spark, path, o, time=None), str(tmp_path / "delta"), str(tmp_path / "cp")).awaitTermination()
    delta = spark.read.schema(o.schema).parquet(str(tmp_path / "delta")).select(*o.columns)
    got = st.search_with_delta(packed, delta, q, 1000)
    assert {(r["qid"], r["rank"], r["id"]) for r in got.collect()} == {(r["qid"], r["rank"], r["id"]) for r in exact.topk(o, q).collect()}


def test_stream_counts_late_rows_and_repeats(spark, tmp_path):
    from intervalnav.streaming import objects as st

    events = spark.read.parquet(f"{DATA}/events.parquet")
    path = write_in_parts(events, str(tmp_path / "in"), 2)
    events.limit(50).coalesce(1).write.mode("append").parquet(path)  # repeats
    s = st.once(st.stream(spark, path, events, late="40 days", files=1), "event_id")
    run = st.counts(s, "1 day").writeStream.outputMode("complete").format("memory").queryName("daily").trigger(availableNow=True).start()
    run.awaitTermination()
    want = {(r["start"], r["event_type"]): r["n"] for r in st.counts(events, "1 day").collect()}
    assert {(r["start"], r["event_type"]): r["n"] for r in spark.table("daily").collect()} == want


def test_recall_and_interpolation(spark):
    from intervalnav.operators import measures

    q = spark.createDataFrame([(1, 2), (2, 2)], "qid long, k int")
    found, truth = (spark.createDataFrame(x, "qid long, id long") for x in ([(1, 5)], [(1, 5), (1, 6)]))
    got = {r["qid"]: (r["recall_k"], r["recall_min"]) for r in measures.recall(found, truth, q).collect()}
    assert got == {1: (0.5, 0.5), 2: (0.0, None)}
    assert measures.at_recall([(0.9, 100.0), (1.0, 50.0)], 0.95) == pytest.approx(75.0) and measures.at_recall([(0.5, 9.0)], 0.9) is None
