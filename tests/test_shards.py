"""Shards of bounded size: each is built in a task of its own, and whole walks and built times agree with plain forms."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from intervalnav import queries_core, queries_search
from intervalnav.operators import exact, index, kernels, methods
from intervalnav.plans import store
from intervalnav.sources import tables

SF = "/root/testdata/sf0.001"


def _shard(n: int, seed: int = 3) -> kernels.Shard:
    rng = np.random.default_rng(seed)
    lo = rng.integers(0, 12, n).astype(float)
    return kernels.Shard(np.arange(n) * 7 + 2, rng.random((n, 3)), lo, lo + rng.integers(0, 9, n))


def test_every_shard_has_a_task(spark):
    objects = tables.objects(spark, SF)
    packed = index.build(objects, methods.PreFilter(), store.shard_column("hash", 4), 4)
    rows = packed.select("shard", "n", F.spark_partition_id().alias("task")).collect()
    assert len({r["task"] for r in rows}) == len(rows) == 4
    assert sum(r["n"] for r in rows) == objects.count()


@pytest.mark.parametrize("name", ["hcnng", "timestamp_graph", "window_tree"])
def test_baselines_over_several_shards(spark, monkeypatch, name):
    monkeypatch.setattr(queries_core, "SHARD", 120)
    assert queries_core.shards_of(spark, SF) > 1
    load = queries_search.BASELINES[name][1]
    want = exact.topk(queries_core.objects(spark, SF, intervals=queries_core.WORKLOADS[load][0]), queries_core.workload(spark, SF, load, 60))
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(queries_search.QUERIES[f"q_bl_{name}"](spark, SF)) == rows(queries_core.rounded(want))


def test_whole_walk_enters_what_is_reached():
    s = _shard(40)
    src, dst = np.array([0, 1, 2, 5, 6, 0]), np.array([1, 2, 0, 6, 5, 9])
    graph = kernels.Adjacency.of(40, src, dst, np.array([3, 1, 3, 3, 3, 2]))
    order = lambda of: sorted(of, key=lambda i: (((s.x[i] - s.x[3]) ** 2).sum(), s.ids[i]))
    for _ in range(2):  # the second walk is remembered
        got, effort = kernels.beam(s, graph, [0], s.x[3], 40, kernels.WITHIN, None)
        assert got == order([0, 1, 2]) and effort == {"hops": 3, "edges": 4, "distances": 3}
    ok = np.ones(40, bool)
    ok[2] = False
    assert kernels.beam(s, graph, [0], s.x[3], 40, kernels.WITHIN, ok)[0] == order([0, 1])
    assert kernels.beam(s, graph, [0, 5], s.x[3], 40, kernels.COVERS, None, returns=ok)[0] == order([0, 1, 9, 5, 6])
    assert (kernels.WITHIN, 0) in graph.walks


def test_lifetimes_are_the_plain_graph_of_every_moment():
    s = _shard(45)
    got = methods.Lifetimes().build(s)
    for t in np.arange(0, 20, 0.5):
        of = np.flatnonzero((s.lo <= t) & (s.hi >= t))
        if not len(of):
            continue
        part = methods._sub(s, of)
        want = kernels.prune(part, np.arange(len(of)), kernels.everyone(len(of)), None, "none")
        alive = (got["from"] <= t) & (got["to"] >= t)
        assert set(zip(got["src"][alive], got["dst"][alive])) == set(zip(of[want.src], of[want.dst]))
