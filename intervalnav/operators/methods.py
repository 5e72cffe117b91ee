"""Search methods on one shard: the interval-aware graph, its variants, and the baselines.

Each method builds arrays from a shard and answers a query with them. Graph baselines are built in batches
(pools, occlusion, reverse edges) where their published forms insert one object at a time; what is simplified
is said in the class. Answers of all methods are valid objects by (distance, id).
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from . import kernels as kn
from .exact import valid
from .kernels import Adjacency, Entries, Shard

Arrays = dict[str, np.ndarray]


@dataclass
class Query:
    q: np.ndarray
    ql: float
    qr: float
    k: int
    mode: str
    ef: int


def _hash(ids: np.ndarray, salt: int) -> np.ndarray:
    """Uniform numbers in (0, 1) from ids."""
    x = (ids.astype(np.uint64) + np.uint64(salt)) * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(31)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(29)
    return ((x >> np.uint64(11)).astype(float) + 0.5) / 2.0**53


def _nearest(shard: Shard, of: np.ndarray, query: Query) -> list[int]:
    diff = shard.x[of] - query.q
    d = np.einsum("ij,ij->i", diff, diff)
    return of[np.lexsort((shard.ids[of], d))[: query.k]].tolist()


def _once(data: Arrays, name: str, make):
    """A structure of a shard, made at its first query."""
    if name not in data:
        data[name] = make()
    return data[name]


def _first(near: list[int], ok, k: int) -> list[int]:
    """The first k that are ok."""
    of = np.array(near, np.int64)
    return of[ok[of]][:k].tolist()


def _ok(shard: Shard, query: Query) -> np.ndarray:
    return valid(query.mode, shard.lo, shard.hi, query.ql, query.qr)


class Tested:
    """Validity of objects, tested where asked for: a beam pays for the neighbours that it meets, not for all objects."""

    def __init__(self, shard: Shard, query: Query):
        self.shard, self.query = shard, query

    def __getitem__(self, i):
        s, q = self.shard, self.query
        return valid(q.mode, s.lo[i], s.hi[i], q.ql, q.qr) if q.mode != "any" else np.ones(np.shape(i), bool)


def _medoid(shard: Shard) -> int:
    diff = shard.x - shard.x.mean(0)
    return int(np.einsum("ij,ij->i", diff, diff).argmin())


def _both_ways(n: int, src: np.ndarray, dst: np.ndarray) -> list[np.ndarray]:
    return kn.grouped(n, np.concatenate([src, dst]), np.concatenate([dst, src]))


def _sub(shard: Shard, of: np.ndarray) -> Shard:
    return Shard(shard.ids[of], shard.x[of], shard.lo[of], shard.hi[of])


@dataclass
class Method:
    def build(self, shard: Shard) -> Arrays:
        return {}

    def search(self, shard: Shard, data: Arrays, query: Query) -> tuple[list[int], dict]:
        raise NotImplementedError


@dataclass
class PreFilter(Method):
    """All valid objects are compared."""

    def search(self, shard, data, query):
        of = np.flatnonzero(_ok(shard, query))
        return _nearest(shard, of, query), {"hops": 0, "edges": 0, "distances": len(of)}


@dataclass
class PostFilter(Method):
    """The ``oversample`` nearest of all objects, then the valid ones among them; ``adaptive`` doubles that while fewer than k remain."""

    oversample: int = 100
    adaptive: bool = False

    def search(self, shard, data, query):
        n, ok, m = len(shard.ids), _ok(shard, query), self.oversample
        while True:
            near = _nearest(shard, np.arange(n), Query(query.q, 0, 0, m, "any", m))
            found = _first(near, ok, query.k)
            if not self.adaptive or len(found) == query.k or m >= n:
                return found, {"hops": 0, "edges": 0, "distances": n}
            m *= 2


@dataclass
class IntervalGraph(Method):
    """The two-bit graph: exact (all others as candidates) or bounded (pools, degree budgets and repair rounds)."""

    exact: bool = False
    spatial: int = 32
    attribute: int = 64
    budget: int | None = 64
    rounds: int = 3
    repair: bool = True
    keys: tuple[str, ...] = ("lo", "hi", "mid", "len")
    pool: str = "descent"
    disjoint: str = "drop"
    witness: str = "interval"
    visited: str = "push"
    entry: str = "rank"

    def pools(self, shard: Shard) -> list[np.ndarray]:
        n = len(shard.ids)
        if self.exact:
            return kn.everyone(n)
        s = kn.nearest_lists(shard, self.spatial) if self.pool == "exact" else kn.neighbours(shard, self.spatial)
        a = kn.rank_neighbours(shard, self.attribute, self.keys)
        return kn.grouped(n, np.concatenate([s[0], a[0]]), np.concatenate([s[1], a[1]]))

    def build(self, shard):
        n = len(shard.ids)
        if not n:
            return {c: np.zeros(0, np.int64) for c in ("src", "dst", "d", "bits")}
        got = kn.refine(shard, self.pools(shard), None if self.exact else self.budget, 1 if self.exact else self.rounds, self.repair, self.witness, self.disjoint, repairs=not self.exact)
        return {"src": got.src, "dst": got.dst, "d": got.d, "bits": got.bits, "repair_src": got.repair_src, "repair_dst": got.repair_dst}

    def search(self, shard, data, query):
        if "graph" not in data:
            data["graph"] = Adjacency.of(len(shard.ids), data["src"], data["dst"], data["bits"])
            data["entries"] = Entries.of(shard)
        ok = Tested(shard, query)
        if self.entry == "hash":  # any valid object will do
            of = np.flatnonzero(_ok(shard, query))
            start = int(of[_hash(of, 5).argmin()]) if len(of) else -1
        else:
            start = data["entries"].find(query.mode, query.ql, query.qr)
        bit = kn.COVERS if query.mode == "covers" else kn.WITHIN
        found, effort = kn.beam(shard, data["graph"], [start] if start >= 0 else [], query.q, max(query.ef, query.k), bit, ok, self.visited)
        return found[: query.k], effort


@dataclass
class PlainGraph(Method):
    """Occlusion without intervals. ``how``: "post" (all objects, filter after, beam doubled while fewer than k
    remain), "in" (valid objects only, from the entry object) or "result" (all traversed, valid ones collected)."""

    how: str = "post"
    pool_size: int | None = None  # None: all others
    budget: int | None = None
    oversample: int = 1

    def links(self, shard: Shard) -> tuple[np.ndarray, np.ndarray]:
        pool = kn.everyone(len(shard.ids)) if self.pool_size is None else kn.grouped(len(shard.ids), *kn.neighbours(shard, self.pool_size))
        got = kn.prune(shard, np.arange(len(shard.ids)), pool, self.budget, "none", repairs=False)
        return got.src, got.dst

    def start(self, shard: Shard) -> int:
        return _medoid(shard)

    def build(self, shard):
        if not len(shard.ids):
            return {"src": np.zeros(0, np.int64), "dst": np.zeros(0, np.int64), "start": np.zeros(0, np.int64)}
        src, dst = self.links(shard)
        return {"src": src, "dst": dst, "start": np.array([self.start(shard)])}

    def starts(self, shard: Shard, data: Arrays, query: Query) -> list[int]:
        return data["start"].tolist()

    def search(self, shard, data, query):
        n = len(shard.ids)
        if not n:
            return [], {}
        if "graph" not in data:
            data["graph"] = Adjacency.of(n, data["src"], data["dst"], np.full(len(data["src"]), 3, np.int8))
            data["entries"] = Entries.of(shard)
        ok = Tested(shard, query)
        ef = max(query.ef, query.k)
        if self.how == "in":
            start = data["entries"].find(query.mode, query.ql, query.qr)
            found, effort = kn.beam(shard, data["graph"], [start] if start >= 0 else [], query.q, ef, 3, ok)
            return found[: query.k], effort
        if self.how == "result":
            found, effort = kn.beam(shard, data["graph"], self.starts(shard, data, query), query.q, ef, 3, None, returns=ok)
            return found[: query.k], effort
        ef *= self.oversample
        while True:
            near, effort = kn.beam(shard, data["graph"], self.starts(shard, data, query), query.q, ef, 3, None)
            found = _first(near, ok, query.k)
            if len(found) == query.k or ef >= n:
                return found, effort
            ef *= 2


@dataclass
class Layered(PlainGraph):
    """Layers by a geometric level law; each layer's links come from its own pools and occlusion, with reverse links
    and a cap (twice M on the lowest). The descent from the top is greedy. Built layer by layer, not by insertion."""

    m: int = 16
    ef_c: int = 64

    def levels(self, shard: Shard) -> np.ndarray:
        return np.floor(-np.log(_hash(shard.ids, 1)) / np.log(self.m)).astype(np.int64)

    def build(self, shard):
        n = len(shard.ids)
        empty = np.zeros(0, np.int64)
        if not n:
            return {"src": empty, "dst": empty, "upper_src": empty, "upper_dst": empty, "upper_level": empty, "start": empty}
        level = self.levels(shard)
        top = int(np.lexsort((shard.ids, -level))[0])
        out: list[list[np.ndarray]] = [[], [], []]
        for lv in range(int(level.max()) + 1):
            of = np.flatnonzero(level >= lv)
            part = _sub(shard, of)
            pool = kn.grouped(len(of), *kn.neighbours(part, self.ef_c))
            got = kn.prune(part, np.arange(len(of)), pool, self.m, "none")
            back = kn.prune(part, np.arange(len(of)), _both_ways(len(of), got.src, got.dst), 2 * self.m if lv == 0 else self.m, "none")
            first = int(np.flatnonzero(of == top)[0])  # all of a layer is reached from the topmost object
            joined = _connected(part, back.src, back.dst, first)
            for column, x in zip(out, (of[joined[0]], of[joined[1]], np.full(len(joined[0]), lv)), strict=True):
                column.append(x)
        src, dst, lv = (np.concatenate(c) for c in out)
        return {"src": src[lv == 0], "dst": dst[lv == 0], "upper_src": src[lv > 0], "upper_dst": dst[lv > 0], "upper_level": lv[lv > 0], "start": np.array([top])}

    def starts(self, shard, data, query):
        if "layers" not in data:
            lv = data["upper_level"]
            data["layers"] = [Adjacency.of(len(shard.ids), data["upper_src"][lv == i], data["upper_dst"][lv == i], np.full(int((lv == i).sum()), 3)) for i in range(1, int(lv.max(initial=0)) + 1)]
        at = int(data["start"][0])
        for layer in reversed(data["layers"]):
            at = (kn.beam(shard, layer, [at], query.q, 1, 3, None)[0] or [at])[0]
        return sorted({at, int(data["start"][0])})


def _connected(shard: Shard, src: np.ndarray, dst: np.ndarray, root: int) -> tuple[np.ndarray, np.ndarray]:
    """The links, and more from the nearest reached object to each that the root does not reach."""
    n = len(shard.ids)
    graph = Adjacency.of(n, src, dst, np.full(len(src), 3))
    reached = np.zeros(n, bool)
    add_s, add_d = [], []
    stack = [root]
    reached[root] = True
    while True:
        while stack:
            u = stack.pop()
            near = graph.dst[graph.begin[u] : graph.begin[u + 1]]
            near = np.unique(near[~reached[near]])
            reached[near] = True
            stack += near.tolist()
        rest = np.flatnonzero(~reached)
        if not len(rest):
            return np.concatenate([src, np.array(add_s, np.int64)]), np.concatenate([dst, np.array(add_d, np.int64)])
        v = int(rest[0])
        of = np.flatnonzero(reached)
        diff = shard.x[of] - shard.x[v]
        add_s.append(int(of[np.einsum("ij,ij->i", diff, diff).argmin()]))
        add_d.append(v)
        reached[v] = True
        stack = [v]


@dataclass
class Slack(PlainGraph):
    """Robust pruning with slack: pools from neighbour lists and pseudo-random links, one pass without and one with
    slack, reverse links pruned again; the medoid is the start. Pools stand for the beams of the published form."""

    m: int = 16
    ef_c: int = 64
    alpha: float = 1.2

    def links(self, shard):
        n = len(shard.ids)
        s, d = kn.neighbours(shard, self.ef_c)
        far = np.stack([np.argsort(_hash(shard.ids, 17 + i), kind="stable") for i in range(min(8, n))])
        rs, rd = np.tile(np.arange(n), len(far)), far.ravel()
        for alpha in (1.0, self.alpha):
            got = kn.prune(shard, np.arange(n), kn.grouped(n, np.concatenate([s, rs]), np.concatenate([d, rd])), self.m, "none", alpha=alpha**2)
            both = _both_ways(n, got.src, got.dst)
            got = kn.prune(shard, np.arange(n), both, self.m, "none", alpha=alpha**2)
            s, d = np.concatenate([s, got.src]), np.concatenate([d, got.dst])
        return _connected(shard, got.src, got.dst, _medoid(shard))


@dataclass
class Spanning(PlainGraph):
    """Occlusion over neighbour lists and their neighbours, reverse links, and a spanning repair from the medoid."""

    m: int = 16
    ef_c: int = 64

    def links(self, shard):
        n = len(shard.ids)
        s, d = kn.neighbours(shard, self.ef_c)
        lists = kn.grouped(n, s, d)
        wide = [np.setdiff1d(np.concatenate([p, *(lists[j][:4] for j in p[:16])]), [i]) for i, p in enumerate(lists)]
        got = kn.prune(shard, np.arange(n), wide, self.m, "none")
        back = kn.prune(shard, np.arange(n), _both_ways(n, got.src, got.dst), self.m, "none")
        return _connected(shard, back.src, back.dst, _medoid(shard))


@dataclass
class Clustered(PlainGraph):
    """The union, over several random two-pivot hierarchies, of degree-capped minimum spanning trees of their leaves."""

    trees: int = 10
    leaf: int = 100
    degree: int = 5

    def leaves(self, shard: Shard, seed: int) -> list[np.ndarray]:
        rng, out, todo = np.random.default_rng(seed), [], [np.arange(len(shard.ids))]
        while todo:
            of = todo.pop()
            if len(of) <= self.leaf:
                out.append(of)
                continue
            a, b = rng.choice(of, 2, replace=False)
            left = ((shard.x[of] - shard.x[a]) ** 2).sum(1) < ((shard.x[of] - shard.x[b]) ** 2).sum(1)
            if left.all() or not left.any():  # copies of one point
                left = np.arange(len(of)) < len(of) // 2
            todo += [of[left], of[~left]]
        return out

    def links(self, shard):
        src, dst = [], []
        for t in range(self.trees):
            for of in self.leaves(shard, t):
                i, j = np.triu_indices(len(of), 1)
                d = shard.sq(of[i], of[j])
                parent, degree = list(range(len(of))), np.zeros(len(of), np.int64)

                def find(x: int, parent=parent) -> int:
                    while parent[x] != x:
                        parent[x] = parent[parent[x]]
                        x = parent[x]
                    return x

                left = len(of) - 1
                for e in np.lexsort((j, i, d)).tolist():
                    if not left:
                        break
                    a, b = int(i[e]), int(j[e])
                    if degree[a] < self.degree and degree[b] < self.degree and (x := find(a)) != (y := find(b)):
                        parent[x] = y
                        degree[a] += 1
                        degree[b] += 1
                        src += [of[a], of[b]]
                        dst += [of[b], of[a]]
                        left -= 1
        pairs = np.unique(np.stack([np.array(src, np.int64), np.array(dst, np.int64)], 1), axis=0)
        return _connected(shard, pairs[:, 0], pairs[:, 1], _medoid(shard))


@dataclass
class TwoHop(PlainGraph):
    """Dense lists without occlusion beyond M nearest; invalid neighbours are looked through at theirs."""

    how: str = "in"
    m: int = 16
    gamma: int = 4

    def links(self, shard):
        s, d = kn.neighbours(shard, self.m * self.gamma)
        both = _both_ways(len(shard.ids), s, d)
        return np.repeat(np.arange(len(both)), [len(b) for b in both]), np.concatenate(both) if both else d

    def search(self, shard, data, query):
        n = len(shard.ids)
        if "graph" not in data:
            data["graph"] = Adjacency.of(n, data["src"], data["dst"], np.full(len(data["src"]), 3, np.int8))
            data["entries"] = Entries.of(shard)
        start = data["entries"].find(query.mode, query.ql, query.qr)
        found, effort = kn.beam(shard, data["graph"], [start] if start >= 0 else [], query.q, max(query.ef, query.k), 3, Tested(shard, query), hops=2)
        return found[: query.k], effort


@dataclass
class Partitioned(Method):
    """Intervals split at medians of their lower and upper ends in turn, a backbone graph for each part; a query goes
    to the parts that can hold valid objects, filters where a part is not wholly valid, and merges."""

    backbone: PlainGraph = field(default_factory=Layered)
    leaf: int = 100

    def parts(self, shard: Shard) -> list[np.ndarray]:
        out, todo = [], [(np.arange(len(shard.ids)), 0)]
        while todo:
            of, depth = todo.pop()
            if len(of) <= self.leaf:
                out.append(np.sort(of))
                continue
            v = (shard.lo, shard.hi)[depth % 2][of]
            order = np.lexsort((shard.ids[of], v))
            todo += [(of[order[: len(of) // 2]], depth + 1), (of[order[len(of) // 2 :]], depth + 1)]
        return out

    def build(self, shard):
        out: Arrays = {}
        for i, of in enumerate(self.parts(shard)):
            out[f"part{i}"] = of
            out |= {f"p{i}_{k}": v for k, v in self.backbone.build(_sub(shard, of)).items()}
        return out

    def search(self, shard, data, query):
        found, total = [], {"hops": 0, "edges": 0, "distances": 0}
        for i in range(sum(k.startswith("part") for k in data)):
            of = data[f"part{i}"]
            if not len(of) or not _ok(shard, query)[of].any():
                continue
            if f"own{i}" not in data:
                data[f"own{i}"] = (_sub(shard, of), {k.split("_", 1)[1]: v for k, v in data.items() if k.startswith(f"p{i}_")})
            part, arrays = data[f"own{i}"]
            got, effort = self.backbone.search(part, arrays, query)
            found += of[got].tolist()
            total = {k: total[k] + effort.get(k, 0) for k in total}
        return _nearest(shard, np.array(found, np.int64), query) if found else [], total


@dataclass
class Lifetimes(Method):
    """Plain graphs of all moments in one: an edge has the times at which no valid nearer neighbour occludes it."""

    pool_size: int | None = None

    def build(self, shard):
        n = len(shard.ids)
        pools = kn.everyone(n) if self.pool_size is None else kn.grouped(n, *kn.neighbours(shard, self.pool_size))
        rows: list[tuple[int, int, float, float]] = []
        for u in range(n):
            p = pools[u]
            d = shard.sq(np.full(len(p), u), p)
            order = np.lexsort((shard.ids[p], d))
            v, d = p[order], d[order]
            # What may be free of it: times of both, cut at the ends; what is taken from the middle is found at its turn.
            a, b = np.maximum(shard.lo[u], shard.lo[v]), np.minimum(shard.hi[u], shard.hi[v])
            owner, owner_d, live = np.zeros(0, np.int64), np.zeros(0), np.zeros((0, 2))
            i = 0
            while True:
                some = a[i:] <= b[i:]
                if not some.any():
                    break
                i += int(some.argmax())
                if 2 * np.count_nonzero(some) < len(some):
                    stay = i + np.flatnonzero(a[i:] <= b[i:])
                    v, d, a, b, i = v[stay], d[stay], a[stay], b[stay], 0
                w = int(v[i])
                near = (owner_d < d[i]) & (live[:, 0] <= b[i]) & (live[:, 1] >= a[i])
                near[near] = shard.from_one(w, owner[near]) < d[i]
                free = _minus(float(a[i]), float(b[i]), live[near])
                if free:
                    rows += [(u, w, x, y) for x, y in free]
                    owner, owner_d, live = np.append(owner, [w] * len(free)), np.append(owner_d, [d[i]] * len(free)), np.vstack([live, free])
                    later = i + 1 + np.flatnonzero((a[i + 1 :] <= b[i + 1 :]) & (d[i] < d[i + 1 :]))
                    later = later[shard.from_one(w, v[later]) < d[later]]
                    for x, y in free:
                        low, high = later[(x <= a[later]) & (a[later] <= y)], later[(x <= b[later]) & (b[later] <= y)]
                        a[low] = np.nextafter(y, np.inf)
                        b[high] = np.nextafter(x, -np.inf)
                i += 1
        got = np.array(rows, float).reshape(-1, 4)
        return {"src": got[:, 0].astype(np.int64), "dst": got[:, 1].astype(np.int64), "from": got[:, 2], "to": got[:, 3]}

    def search(self, shard, data, query):
        entries = _once(data, "entries", lambda: Entries.of(shard))
        start = entries.find("covers", query.ql, query.qr)
        alive = (data["from"] <= query.ql) & (data["to"] >= query.qr)
        graph = Adjacency.of(len(shard.ids), data["src"][alive], data["dst"][alive], np.full(int(alive.sum()), 3))
        found, effort = kn.beam(shard, graph, [start] if start >= 0 else [], query.q, max(query.ef, query.k), 3, Tested(shard, query))
        return found[: query.k], effort


def _minus(a: float, b: float, taken: np.ndarray) -> list[tuple[float, float]]:
    """What is left of [a, b] without closed intervals (rows); ends that do not belong to it are moved by the least step."""
    out = []
    for x, y in taken[np.argsort(taken[:, 0], kind="stable")].tolist():
        if x > a:
            out.append((a, min(b, float(np.nextafter(x, -np.inf)))))
        a = max(a, float(np.nextafter(y, np.inf)))
        if a > b:
            return out
    return [*out, (a, b)]


@dataclass
class Rectangles(Method):
    """Scalar objects: an edge holds for the ranges [l, r] with l in one interval and r in another, since a nearer
    neighbour occludes it in every range that has that neighbour. ``ordered``: links only to earlier values, and back,
    as insertion by value gives; otherwise each object judges all its candidates at once, in any order."""

    ordered: bool = False
    pool_size: int | None = None

    def build(self, shard):
        n, a = len(shard.ids), shard.lo
        pools = kn.everyone(n) if self.pool_size is None else kn.grouped(n, *kn.neighbours(shard, self.pool_size))
        rank = np.empty(n, np.int64)
        rank[np.lexsort((shard.ids, a))] = np.arange(n)
        rows: list[np.ndarray] = []
        for u in range(n):
            p = pools[u]
            if self.ordered:
                p = p[rank[p] < rank[u]]
            d = shard.sq(np.full(len(p), u), p)
            order = np.lexsort((shard.ids[p], d))
            # A range holds both ends: l up to the lesser value and r from the greater.
            v, d = p[order], d[order]
            l0, l1, r0, r1 = np.full(len(v), -np.inf), np.minimum(a[u], a[v]), np.maximum(a[u], a[v]), np.full(len(v), np.inf)
            # Those that nobody occludes, even in part, occlude; what occludes only in part leaves the edge, which is safe.
            i = 0
            while i < len(v):
                if l0[i] == -np.inf and r1[i] == np.inf:
                    x = a[v[i]]
                    near = i + 1 + np.flatnonzero((d[i] < d[i + 1 :]) & (shard.sq(np.full(len(v) - i - 1, v[i]), v[i + 1 :]) < d[i + 1 :]))
                    under, over = near[x < l1[near]], near[x > r0[near]]
                    l0[near[(l1[near] <= x) & (x <= r0[near])]] = np.inf
                    l0[under] = np.maximum(l0[under], np.nextafter(x, np.inf))
                    r1[over] = np.minimum(r1[over], np.nextafter(x, -np.inf))
                    stay = (l0 <= l1) & (r0 <= r1)
                    if not stay.all():  # none of those up to i is among the others
                        v, d, l0, l1, r0, r1 = (y[stay] for y in (v, d, l0, l1, r0, r1))
                i += 1
            kept = np.stack([v, l0, l1, r0, r1], 1)
            own = np.full((len(kept), 1), u)
            rows.append(np.hstack([own, kept]))
            if self.ordered:
                rows.append(np.hstack([kept[:, :1], own, kept[:, 1:]]))
        got = np.concatenate(rows).reshape(-1, 6) if rows else np.zeros((0, 6))
        return {"src": got[:, 0].astype(np.int64), "dst": got[:, 1].astype(np.int64), "l0": got[:, 2], "l1": got[:, 3], "r0": got[:, 4], "r1": got[:, 5]}

    def search(self, shard, data, query):
        entries = _once(data, "entries", lambda: Entries.of(shard))
        start = entries.find("within", query.ql, query.qr)
        on = (data["l0"] <= query.ql) & (query.ql <= data["l1"]) & (data["r0"] <= query.qr) & (query.qr <= data["r1"])
        graph = Adjacency.of(len(shard.ids), data["src"][on], data["dst"][on], np.full(int(on.sum()), 3))
        found, effort = kn.beam(shard, graph, [start] if start >= 0 else [], query.q, max(query.ef, query.k), 3, Tested(shard, query))
        return found[: query.k], effort


@dataclass
class RankTree(Method):
    """Windows of ranks in a tree, a small plain graph for each. ``how``: "edges" takes an object's links level by
    level from the widest window on, those inside the range only; "cover" searches the fewest windows that make up the
    range; "smallest" searches the smallest window (they overlap by half) around the range and filters after."""

    how: str = "edges"
    fan: int = 2
    leaf: int = 32
    budget: int | None = 32

    def windows(self, n: int) -> list[tuple[int, int, int]]:
        """(level, begin, end) of every window."""
        out, width, level = [], n, 0
        while n:
            step = max(1, width // 2) if self.how == "smallest" else width
            out += [(level, a, min(n, a + width)) for a in range(0, n, step) if a == 0 or a + width - step < n]
            if width <= self.leaf:
                break
            width, level = -(-width // self.fan), level + 1
        return out

    def build(self, shard):
        order = np.lexsort((shard.ids, shard.lo))
        src, dst, lv = [], [], []
        for level, a, b in self.windows(len(order)):
            of = order[a:b]
            part = _sub(shard, of)
            got = kn.prune(part, np.arange(len(of)), kn.everyone(len(of)), self.budget, "none", repairs=False)
            s, d = _connected(part, got.src, got.dst, 0)
            src.append(of[s])
            dst.append(of[d])
            lv.append(np.full(len(s), level * (len(order) + 1) + a))
        if self.how == "edges":  # neighbours in rank are linked, so every range of ranks is connected
            src += [order[1:], order[:-1]]
            dst += [order[:-1], order[1:]]
            lv += [np.full(2 * max(0, len(order) - 1), -1)]
        cat = lambda p: np.concatenate(p) if p else np.zeros(0, np.int64)
        return {"src": cat(src), "dst": cat(dst), "window": cat(lv), "order": order}

    def _graph(self, data: Arrays, n: int, level: int, x: int) -> Adjacency:
        """The links of one window, made at its first query."""

        def make() -> Adjacency:
            on = data["window"] == level * (n + 1) + x
            return Adjacency.of(n, data["src"][on], data["dst"][on], np.full(int(on.sum()), 3))

        return _once(data, f"window{level}_{x}", make)

    def cover(self, n: int, a: int, b: int) -> list[tuple[int, int, int]]:
        """The fewest windows that make up ranks a..b (b not included); what is left in the leaves stands as it is (level -1)."""
        out, todo, all_ = [], [(a, b)], self.windows(n)
        for level in sorted({w[0] for w in all_}):
            rest = []
            for x, y in todo:
                inside = [w for w in all_ if w[0] == level and x <= w[1] and w[2] <= y]
                out += inside
                at = x
                for _, p, q in inside:
                    if at < p:
                        rest.append((at, p))
                    at = q
                if at < y:
                    rest.append((at, y))
            todo = rest
        return out + [(-1, x, y) for x, y in todo]

    def search(self, shard, data, query):
        n, order = len(shard.ids), data["order"]
        ok = _ok(shard, query)
        v = shard.lo[order]
        a, b = int(np.searchsorted(v, query.ql, "left")), int(np.searchsorted(v, query.qr, "right"))
        if query.mode == "any":
            a, b = 0, n
        if a >= b:
            return [], {}
        ef = max(query.ef, query.k)
        if self.how == "edges":
            graph = _once(data, "graph", lambda: Adjacency.of(n, data["src"], data["dst"], np.full(len(data["src"]), 3)))
            found, effort = kn.beam(shard, graph, [int(order[(a + b) // 2])], query.q, ef, 3, ok)
            return found[: query.k], effort
        if self.how == "cover":
            found: list[int] = []
            for level, x, y in self.cover(n, a, b):
                if level < 0:
                    found += order[x:y].tolist()
                    continue
                graph = self._graph(data, n, level, x)
                found += kn.beam(shard, graph, [int(order[x])], query.q, ef, 3, None)[0]
            of = np.unique(np.array(found, np.int64))
            return _nearest(shard, of[ok[of]], query), {"distances": len(of)}
        level, x, y = min((w for w in self.windows(n) if w[1] <= a and b <= w[2]), key=lambda w: (w[2] - w[1], w[1]))
        graph = self._graph(data, n, level, x)
        while True:
            near, effort = kn.beam(shard, graph, [int(order[x])], query.q, ef, 3, None)
            got = _first(near, ok, query.k)
            if len(got) == query.k or ef >= y - x:
                return got, effort
            ef *= 2


@dataclass
class Segmented(Method):
    """Rank segments, and for every object a list of links into each; few valid objects are compared one by one, many
    are filtered after a search over all segments, and between these the lists of the range's segments are followed."""

    segments: int = 8
    low: float = 0.05
    high: float = 0.5
    m: int = 16

    def strategy(self, share: float) -> str:
        return "pre" if share < self.low else "post" if share > self.high else "in"

    def build(self, shard):
        n = len(shard.ids)
        order = np.lexsort((shard.ids, shard.lo))
        seg = np.empty(n, np.int64)
        seg[order] = np.arange(n) * self.segments // max(n, 1)
        src, dst = [], []
        for s in range(self.segments):
            of = np.flatnonzero(seg == s)
            pool = [of[of != i] for i in range(n)]
            got = kn.prune(shard, np.arange(n), pool, self.m, "none", repairs=False)
            src.append(got.src)
            dst.append(got.dst)
        src += [order[1:], order[:-1]]  # neighbours in rank, so that every range is connected
        dst += [order[:-1], order[1:]]
        src_, dst_ = (np.concatenate(c) if c else np.zeros(0, np.int64) for c in (src, dst))
        return dict(zip(("src", "dst"), _connected(shard, src_, dst_, 0) if n else (src_, dst_), strict=True)) | {"seg": seg}

    def search(self, shard, data, query):
        ok = _ok(shard, query)
        how = self.strategy(ok.mean() if len(ok) else 0.0)
        if how == "pre":
            return PreFilter().search(shard, data, query)
        graph = _once(data, "graph", lambda: Adjacency.of(len(ok), data["src"], data["dst"], np.full(len(data["src"]), 3)))
        ef = max(query.ef, query.k)
        if how == "in":
            entries = _once(data, "entries", lambda: Entries.of(shard))
            found, effort = kn.beam(shard, graph, [entries.find(query.mode, query.ql, query.qr)], query.q, ef, 3, ok)
            return found[: query.k], effort
        while True:
            near, effort = kn.beam(shard, graph, [0], query.q, ef, 3, None)
            found = _first(near, ok, query.k)
            if len(found) == query.k or ef >= len(ok):
                return found, effort
            ef *= 2
