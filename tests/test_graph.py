"""Kernels against the definition, the hand-sized fixtures, and the invariants."""

import numpy as np
import pytest

from intervalnav.operators import kernels as kn
from intervalnav.operators.exact import valid
from intervalnav.operators.kernels import Adjacency, Entries, Shard
from intervalnav.operators.methods import IntervalGraph, Query, RankTree, Segmented

W1 = {"A": (21, 11, 8, 13), "B": (0, 16, 11, 15), "C": (16, 19, 9, 11), "D": (15, 13, 5, 15), "E": (22, 11, 0, 7), "F": (7, 9, 3, 11), "G": (15, 16, 0, 14), "H": (2, 5, 6, 12)}
# Neighbours by distance; w: within, c: covers.
EXPECTED = {
    "A": "Ew Dwc Gw Cw", "B": "Fwc Hwc Gc Dc Cw", "C": "Gwc Dw Aw Ew Fw Bw Hw", "D": "Gwc Cw Awc Ec Fwc Hwc Bc",
    "E": "Aw Dc Gc Cw", "F": "Hwc Dwc Bwc Gwc Cw", "G": "Dwc Cwc Aw Ec Fwc Bc", "H": "Fwc Bwc Dwc Cw",
}


def shard_of(rows) -> Shard:
    a = np.array(rows, float)
    return Shard(np.arange(len(a)), a[:, :-2], a[:, -2], a[:, -1])


def random_shard(n=60, dim=3, seed=0) -> Shard:
    rng = np.random.default_rng(seed)
    ends = np.sort(rng.integers(0, 40, (n, 2)), axis=1)
    return shard_of(np.concatenate([rng.integers(0, 9, (n, dim)), ends], 1))


def by_definition(s: Shard, disjoint="drop", witness="interval") -> dict[tuple[int, int], int]:
    """Scan of all others by distance, bit by bit."""
    out = {}
    for u in range(len(s.ids)):
        d = ((s.x - s.x[u]) ** 2).sum(1)
        kept: list[tuple[int, int]] = []
        for v in sorted((i for i in range(len(s.ids)) if i != u), key=lambda i: (d[i], i)):
            lo, hi = max(s.lo[u], s.lo[v]), min(s.hi[u], s.hi[v])
            bits = 3 if lo <= hi or disjoint == "keep" or witness == "none" else 1
            for w, b in kept:
                if d[w] < d[v] and ((s.x[w] - s.x[v]) ** 2).sum() < d[v]:
                    if witness == "none":
                        bits = 0
                        break
                    if b & 1 and s.lo[w] >= min(s.lo[u], s.lo[v]) and s.hi[w] <= max(s.hi[u], s.hi[v]):
                        bits &= ~1
                    if b & 2 and (lo > hi or s.lo[w] <= lo and s.hi[w] >= hi):
                        bits &= ~2
            if bits:
                kept.append((v, bits))
                out[u, v] = bits
    return out


def edges(s: Shard, **kw) -> dict[tuple[int, int], int]:
    got = kn.prune(s, np.arange(len(s.ids)), kn.everyone(len(s.ids)), None, **kw)
    return dict(zip(zip(got.src.tolist(), got.dst.tolist(), strict=True), got.bits.tolist(), strict=True))


def test_four_pruning_cases():
    s = shard_of(list(W1.values()))
    names = list(W1)
    want = {(names.index(u), names.index(x[0])): ("w" in x[1:]) + 2 * ("c" in x[1:]) for u, line in EXPECTED.items() for x in line.split()}
    assert edges(s) == want


@pytest.mark.parametrize("seed", range(4))
@pytest.mark.parametrize("how", [{}, {"disjoint": "keep"}, {"witness": "none"}])
def test_prune_is_the_definition_with_ties_and_copies(seed, how):
    s = random_shard(seed=seed)
    assert edges(s, **how) == by_definition(s, **how)


def test_strictness_and_disjoint_pairs():
    tie = shard_of([(0, 0, 0, 1), (5, 0, 0, 1), (4, 3, 0, 1)])
    assert edges(tie)[0, 1] and edges(tie)[0, 2]
    apart = shard_of([(0, 0, 0, 1), (1, 0, 2, 3)])
    assert edges(apart)[0, 1] == 1 and edges(apart, disjoint="keep")[0, 1] == 3


def test_entry_lookup():
    rows = [(0, 0, 3), (0, 1, 10), (0, 2, 6), (0, 3, 5), (0, 4, 12), (0, 5, 7), (0, 6, 9)]
    e = Entries.of(shard_of(rows))
    for mode, ql, qr, want in [("within", 2, 6, 4), ("covers", 4.5, 9.5, 5), ("within", 5, 6, 0), ("within", 7, 9, 0), ("covers", 4.5, 13, 0), ("covers", -1, 0, 0)]:
        assert e.find(mode, ql, qr) == want - 1  # 0: none


def test_visited_marks():
    s = shard_of([(3, 0, 1), (2, 0, 1), (0, 0, 1)])  # s, a, t
    graph = Adjacency.of(3, np.array([0, 0, 1]), np.array([2, 1, 2]), np.array([2, 3, 1]))
    ok = np.ones(3, bool)
    assert kn.beam(s, graph, [0], np.array([0.0]), 3, kn.WITHIN, ok)[0][0] == 2
    assert kn.beam(s, graph, [0], np.array([0.0]), 3, kn.WITHIN, ok, "touch")[0][0] == 1


@pytest.mark.parametrize("mode", ["within", "covers", "any"])
@pytest.mark.parametrize("method", [IntervalGraph(exact=True)])
def test_full_beam_equals_brute_force(mode, method):
    s = random_shard(80, 4, 5)
    data = method.build(s)
    rng = np.random.default_rng(1)
    for _ in range(60):
        ql, qr = sorted(rng.integers(0, 40, 2).tolist())
        q = rng.integers(0, 9, 4).astype(float)
        of = np.flatnonzero(valid(mode, s.lo, s.hi, ql, qr))
        want = of[np.lexsort((of, ((s.x[of] - q) ** 2).sum(1)))][:10].tolist()
        assert method.search(s, data, Query(q, ql, qr, 10, mode, 1000))[0] == want


@pytest.mark.parametrize("rows", [[], [(0, 0, 1)], [(0, 0, 1), (0, 0, 1)]])
def test_small_shards(rows):
    s = shard_of(rows) if rows else Shard(np.zeros(0, np.int64), np.zeros((0, 1)), np.zeros(0), np.zeros(0))
    for method in (IntervalGraph(exact=True), IntervalGraph(spatial=4, attribute=8, rounds=2)):
        found, _ = method.search(s, method.build(s), Query(np.array([0.0]), 0, 1, 5, "within", 5))
        assert sorted(found) == list(range(len(rows)))


def test_heredity_of_one_pass_without_budget():
    s = random_shard(70, 3, 9)
    of = np.flatnonzero(valid("within", s.lo, s.hi, 5, 33))
    part = Shard(s.ids[of], s.x[of], s.lo[of], s.hi[of])
    own = {(int(of[a]), int(of[b])) for (a, b), bits in edges(part).items() if bits & 1}
    cut = {(a, b) for (a, b), bits in edges(s).items() if bits & 1 and a in of and b in of}
    assert own == cut


def test_descent_finds_neighbours():
    rng = np.random.default_rng(2)
    s = Shard(np.arange(400), rng.random((400, 6)), np.zeros(400), np.ones(400))
    near, exact = (set(zip(*(x.tolist() for x in f(s, 12)), strict=True)) for f in (kn.descent, kn.nearest_lists))
    assert len(near & exact) > 0.9 * len(exact)


def test_rounds_must_be_positive():
    with pytest.raises(ValueError):
        kn.refine(random_shard(5), kn.everyone(5), None, 0)


def test_window_cover_is_the_range():
    tree = RankTree("cover", leaf=8)
    for a, b in [(0, 100), (3, 77), (50, 51), (8, 16)]:
        spans = sorted((x, y) for _, x, y in tree.cover(100, a, b))
        assert spans[0][0] == a and spans[-1][1] == b and all(p[1] == q[0] for p, q in zip(spans, spans[1:], strict=False))


def test_segment_strategy():
    assert [Segmented().strategy(x) for x in (0.01, 0.2, 0.9)] == ["pre", "in", "post"]
