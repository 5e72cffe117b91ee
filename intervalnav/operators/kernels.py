"""NumPy kernels on the objects of one shard: occlusion with interval witnesses, and the beam search.

They hold a shard in memory (bounded by the shard size); everything that crosses shards is DataFrame code.
"""

from __future__ import annotations

import heapq
from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np

WITHIN, COVERS = 1, 2


@dataclass
class Shard:
    """Objects of one shard in the order of their ids."""

    ids: np.ndarray
    x: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    _table: np.ndarray | None = field(default=None, repr=False)

    TABLE = 12_000  # up to so many objects all distances are kept (1.2 GB at most)

    def sq(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Squared distances of index arrays of one shape (b may have more dimensions on the right)."""
        if len(self.ids) <= self.TABLE:
            if self._table is None:
                self._table = np.empty((len(self.ids), len(self.ids)))
                for i, v in enumerate(self.x):
                    self._table[i] = ((self.x - v) ** 2).sum(1)
            return self._table[a, b]
        a, b = np.broadcast_arrays(a, b)
        diff = self.x[a.ravel()] - self.x[b.ravel()]
        return np.einsum("ij,ij->i", diff, diff).reshape(a.shape)


    def from_one(self, a: int, b: np.ndarray) -> np.ndarray:
        """Squared distances of one object and others."""
        if self._table is None:
            return self.sq(np.full(len(b), a), b)
        return self._table[a].take(b)


@dataclass
class Pruned:
    src: np.ndarray
    dst: np.ndarray
    d: np.ndarray
    bits: np.ndarray
    repair_src: np.ndarray
    repair_dst: np.ndarray


def prune(shard: Shard, src: np.ndarray, pool: list[np.ndarray], budget: int | None, witness: str = "interval", disjoint: str = "drop", alpha: float = 1.0, repairs: bool = True) -> Pruned:
    """Edges of the sources from their pools (indices without the source, each once).

    All sources take their next candidate in step. A candidate loses a bit to the first kept neighbour that has
    the bit, is strictly nearer to the source and to the candidate, and is a witness: in the hull of the two
    intervals (within), or around what they share (covers). ``witness`` "none" lets every such neighbour take
    both bits, which gives the plain graph; ``alpha`` relaxes nearness for it. Disjoint pairs lose the covers
    bit at once ("drop") or to any neighbour, an empty set being part of everything ("keep"). Without ``repairs``
    the pairs of witness and lost candidate, of which wide pools have millions, are not listed.
    """
    n, width = len(src), pool.n - 1 if isinstance(pool, Everyone) else max((len(p) for p in pool), default=0)
    if width > WIDE:
        return _prune_wide(shard, src, pool, budget, witness, disjoint, alpha, repairs)
    cand = np.full((n, width), -1)
    dist = np.full((n, width), np.inf)
    for i, p in enumerate(pool):
        if len(p):
            d = shard.sq(np.full(len(p), src[i]), p)
            order = np.lexsort((shard.ids[p], d))
            cand[i, : len(p)], dist[i, : len(p)] = p[order], d[order]
    kept = np.full((n, width), -1)
    kept_d = np.full((n, width), np.inf)
    kept_bits = np.zeros((n, width), np.int8)
    used = np.zeros(n, np.int64)
    per_bit = np.zeros((n, 2), np.int64)
    rs, rd = [], []
    lo, hi = shard.lo, shard.hi
    for c in range(width):
        live = np.flatnonzero(cand[:, c] >= 0)
        if not len(live):
            break
        u, v, d = src[live], cand[live, c], dist[live, c]
        m = int(used[live].max())
        bits = np.full(len(live), WITHIN | COVERS, np.int8)
        a_lo, a_hi = np.maximum(lo[u], lo[v]), np.minimum(hi[u], hi[v])  # what they share
        apart = a_lo > a_hi
        if witness == "interval" and disjoint == "drop":
            bits[apart] = WITHIN
        if m:
            w, wd, wb = kept[live, :m], kept_d[live, :m], kept_bits[live, :m]
            spot = np.maximum(w, 0)
            near = (w >= 0) & (wd < d[:, None]) & (alpha * shard.sq(v[:, None], spot) < d[:, None])
            for bit in (WITHIN, COVERS):
                if witness == "none":
                    takes = near & (wb > 0)
                elif bit == WITHIN:
                    takes = near & (wb & bit > 0) & (lo[spot] >= np.minimum(lo[u], lo[v])[:, None]) & (hi[spot] <= np.maximum(hi[u], hi[v])[:, None])
                else:
                    takes = near & (wb & bit > 0) & (((lo[spot] <= a_lo[:, None]) & (hi[spot] >= a_hi[:, None])) | apart[:, None])
                lost = np.flatnonzero(takes.any(1) & (bits & bit > 0))
                bits[lost] &= ~bit
                if repairs:
                    rs.append(w[lost, takes[lost].argmax(1)])
                    rd.append(v[lost])
        if budget is not None:
            for j, bit in enumerate((WITHIN, COVERS)):
                bits[per_bit[live, j] >= budget] &= ~bit
        stay = bits > 0
        at = live[stay]
        kept[at, used[at]], kept_d[at, used[at]], kept_bits[at, used[at]] = v[stay], d[stay], bits[stay]
        used[at] += 1
        for j, bit in enumerate((WITHIN, COVERS)):
            per_bit[at, j] += bits[stay] & bit > 0
    row, col = np.nonzero(kept >= 0)
    cat = lambda parts: np.concatenate(parts).astype(np.int64) if parts else np.zeros(0, np.int64)
    pairs = np.unique(np.stack([cat(rs), cat(rd)], 1), axis=0) if rs else np.zeros((0, 2), np.int64)
    return Pruned(src[row], kept[row, col], kept_d[row, col], kept_bits[row, col], pairs[:, 0], pairs[:, 1])


PRODUCTS = 100_000  # objects of a shard whose neighbour lists are exact
BLOCK = 128  # objects whose distances to all others are looked at together
WIDE = 400  # candidates of a source; more are pruned source by source


def _prune_wide(shard: Shard, src: np.ndarray, pool, budget: int | None, witness: str, disjoint: str, alpha: float, repairs: bool) -> Pruned:
    """The same as ``prune``: each kept neighbour at once takes its bits from all later candidates of its source."""
    lo, hi = shard.lo, shard.hi
    out: list[list[np.ndarray]] = [[] for _ in range(6)]
    held, parts, limit = 0, 0, 1 << 22  # of the listed pairs
    for u, p in zip(src.tolist(), pool, strict=True):
        if not len(p):
            continue
        d = shard.sq(np.full(len(p), u), p)
        order = np.lexsort((shard.ids[p], d))
        v, d = p[order], d[order]
        bits = np.full(len(v), WITHIN | COVERS, np.int8)
        own, shared, hull = (lo[v], hi[v]), (np.maximum(lo[u], lo[v]), np.minimum(hi[u], hi[v])), (np.minimum(lo[u], lo[v]), np.maximum(hi[u], hi[v]))
        apart = shared[0] > shared[1]
        if witness == "interval" and disjoint == "drop":
            bits[apart] = WITHIN
        kept, kept_d, kept_bits, full, i = [], [], [], 0, -1
        per_bit = {WITHIN: 0, COVERS: 0}
        while True:
            live = bits[i + 1 :] & ~np.int8(full) > 0
            if not live.any():
                break
            i += 1 + int(live.argmax())
            if 2 * np.count_nonzero(live) < len(live):  # lost candidates, and those that were looked at, are left behind
                stay = np.flatnonzero(bits > 0) if repairs else np.flatnonzero(bits & ~np.int8(full) > 0)
                stay = stay[stay >= i]
                v, d, bits, apart = (x[stay] for x in (v, d, bits, apart))
                own, shared, hull = (tuple(x[stay] for x in y) for y in (own, shared, hull))
                i = 0
            b, w = int(bits[i]) & ~full, int(v[i])
            kept.append(w)
            kept_d.append(float(d[i]))
            kept_bits.append(b)
            for bit in (WITHIN, COVERS):
                per_bit[bit] += b & bit > 0
                if budget is not None and per_bit[bit] >= budget:
                    full |= bit
            later = slice(i + 1, None)
            at = i + 1 + np.flatnonzero((d[i] < d[later]) & (alpha * shard.from_one(w, v[later]) < d[later]) & (bits[later] > 0))
            gone = np.zeros(len(at), np.int8)
            for bit in (WITHIN, COVERS):
                if witness != "none" and not b & bit:
                    continue
                takes = bits[at] & bit > 0
                if witness != "none" and bit == WITHIN:
                    takes &= (own[0][i] >= hull[0][at]) & (own[1][i] <= hull[1][at])
                elif witness != "none":
                    takes &= (own[0][i] <= shared[0][at]) & (own[1][i] >= shared[1][at]) | apart[at]
                gone[takes] |= bit
                if repairs:
                    out[4].append(np.full(int(takes.sum()), w))
                    out[5].append(v[at[takes]])
            bits[at] &= ~gone
        for column, x in zip(out, (np.full(len(kept), u), np.array(kept, np.int64), np.array(kept_d), np.array(kept_bits, np.int8)), strict=False):
            column.append(x)
        held += sum(len(x) for x in out[4][parts:])
        parts = len(out[4])
        if held > limit:  # each pair once, so that few are held
            pairs = np.unique(np.concatenate(out[4]) * len(shard.ids) + np.concatenate(out[5]))
            out[4], out[5], held, parts, limit = [pairs // len(shard.ids)], [pairs % len(shard.ids)], len(pairs), 1, max(limit, 2 * len(pairs))
    if out[4]:
        pairs = np.unique(np.concatenate(out[4]) * len(shard.ids) + np.concatenate(out[5]))
        out[4], out[5] = [pairs // len(shard.ids)], [pairs % len(shard.ids)]
    types = (np.int64, np.int64, float, np.int8, np.int64, np.int64)
    return Pruned(*(np.concatenate(c).astype(t) if c else np.zeros(0, t) for c, t in zip(out, types, strict=True)))


def grouped(n: int, src: np.ndarray, dst: np.ndarray) -> list[np.ndarray]:
    """The distinct targets of every source 0..n-1, without itself."""
    keys = np.unique((src * n + dst)[src != dst])  # a pair as one number
    return np.split(keys % n, np.searchsorted(keys, np.arange(1, n) * n)) if n else []


class Everyone(Sequence):
    """All others as the pool of each object; a pool is made when it is asked for."""

    def __init__(self, n: int, of: range | None = None):
        self.n, self.of = n, range(n) if of is None else of

    def __len__(self) -> int:
        return len(self.of)

    def __getitem__(self, i):
        return Everyone(self.n, self.of[i]) if isinstance(i, slice) else np.delete(np.arange(self.n), self.of[i])


def everyone(n: int) -> Sequence:
    return Everyone(n)


def refine(shard: Shard, pool: list[np.ndarray], budget: int | None, rounds: int, repair: bool = True, witness: str = "interval", disjoint: str = "drop", chunk: int = 2048, repairs: bool = True) -> Pruned:
    """Rounds of pruning; each starts from what was kept and from the pairs (witness, lost candidate) of the round before."""
    if rounds < 1:
        raise ValueError("at least one round")
    n = len(shard.ids)
    for i in range(rounds):
        parts = [prune(shard, np.arange(a, min(n, a + chunk)), pool[a : a + chunk], budget, witness, disjoint, repairs=repairs) for a in range(0, n, chunk)] or [prune(shard, np.zeros(0, np.int64), [], budget)]
        got = Pruned(*(np.concatenate([getattr(p, f) for p in parts]) for f in Pruned.__dataclass_fields__))
        if i == rounds - 1:
            break
        more = (got.repair_src, got.repair_dst) if repair else (got.src[:0], got.dst[:0])
        pool = grouped(n, np.concatenate([got.src, more[0]]), np.concatenate([got.dst, more[1]]))
    return got


def rank_neighbours(shard: Shard, budget: int, keys: tuple[str, ...] = ("lo", "hi", "mid", "len")) -> tuple[np.ndarray, np.ndarray]:
    h, n = budget // 8, len(shard.ids)
    src, dst = [], []
    for key in keys if h else ():
        v = {"lo": shard.lo, "hi": shard.hi, "mid": shard.lo + shard.hi, "len": shard.hi - shard.lo}[key]
        order = np.lexsort((shard.ids, v))
        for step in range(1, min(h, n - 1) + 1):
            src += [order[step:], order[:-step]]
            dst += [order[:-step], order[step:]]
    cat = lambda p: np.concatenate(p) if p else np.zeros(0, np.int64)
    return cat(src), cat(dst)


def descent(shard: Shard, k: int, rounds: int = 8, sample: int = 16, seed: int = 7, least_change: float = 0.001) -> tuple[np.ndarray, np.ndarray]:
    """Approximate k nearest neighbours within the shard by neighbour descent: (src, dst)."""
    n = len(shard.ids)
    k = min(k, n - 1)
    if k < 1:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    rng = np.random.default_rng(seed)
    now = (np.arange(n)[:, None] + 1 + np.argsort(rng.random((n, min(n - 1, 4 * k))), axis=1)[:, :k]) % n
    d = shard.sq(np.arange(n)[:, None], now)
    new = np.ones_like(now, bool)
    for _ in range(rounds):
        src, dst, fresh = np.repeat(np.arange(n), k), now.ravel(), new.ravel()
        pick = rng.random(len(src)) < min(1.0, sample / k)
        p, m, f = np.concatenate([src[pick], dst[pick]]), np.concatenate([dst[pick], src[pick]]), np.concatenate([fresh[pick]] * 2)
        order = np.argsort(p, kind="stable")
        p, m, f = p[order], m[order], f[order]
        ends = np.searchsorted(p, np.arange(n + 1))
        a, b = [], []
        for i in range(n):
            ms, fs = m[ends[i] : ends[i + 1]][: 4 * sample], f[ends[i] : ends[i + 1]][: 4 * sample]
            x, y = np.triu_indices(len(ms), 1)
            ok = (fs[x] | fs[y]) & (ms[x] != ms[y])
            a.append(ms[x[ok]])
            b.append(ms[y[ok]])
        pairs = np.unique(np.stack([np.concatenate(a + b), np.concatenate(b + a)], 1), axis=0)
        dp = shard.sq(pairs[:, 0], pairs[:, 1])
        s = np.concatenate([src, pairs[:, 0]])
        t = np.concatenate([dst, pairs[:, 1]])
        dd = np.concatenate([d.ravel(), dp])
        is_new = np.concatenate([np.zeros(len(src), bool), np.ones(len(pairs), bool)])
        order = np.lexsort((is_new, t, s))
        s, t, dd, is_new = s[order], t[order], dd[order], is_new[order]
        once = np.r_[True, (s[1:] != s[:-1]) | (t[1:] != t[:-1])]
        s, t, dd, is_new = s[once], t[once], dd[once], is_new[once]
        order = np.lexsort((t, dd, s))
        s, t, dd, is_new = s[order], t[order], dd[order], is_new[order]
        first = np.searchsorted(s, np.arange(n))
        spot = first[:, None] + np.arange(k)
        now, d, new = t[spot], dd[spot], is_new[spot]
        if new.sum() <= least_change * n * k:
            break
    return np.repeat(np.arange(n), k), now.ravel()


def neighbours(shard: Shard, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Lists of k nearest neighbours for pools: exact ones while products of all pairs are the cheaper way, else by descent."""
    return nearest_lists(shard, k) if len(shard.ids) <= PRODUCTS else descent(shard, k)


def nearest_lists(shard: Shard, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Exact k nearest neighbours within the shard, ties by id.

    Products of blocks leave few objects that can be among them (with a margin above their rounding); those are compared.
    """
    n = len(shard.ids)
    k = min(k, n - 1)
    if k < 1:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    norm, dst = np.einsum("ij,ij->i", shard.x, shard.x), []
    margin = 1e-9 * max(1.0, float(norm.max()))
    for a in range(0, n, BLOCK):
        near = norm[None, :] - 2 * shard.x[a : a + BLOCK] @ shard.x.T + norm[a : a + BLOCK, None]
        near[np.arange(len(near)), np.arange(a, a + len(near))] = np.inf
        limit = np.partition(near, k - 1, axis=1)[:, k - 1] + margin
        for i, row in enumerate(near):
            of = np.flatnonzero(row <= limit[i])
            d = shard.sq(np.full(len(of), a + i), of)
            dst.append(of[np.lexsort((shard.ids[of], d))[:k]])
    return np.repeat(np.arange(n), k), np.concatenate(dst)


# ---- search -------------------------------------------------------------------------------------------------


@dataclass
class Entries:
    """Objects in the order of lo, the least hi from each on, and the greatest hi up to each, with their places."""

    lo: np.ndarray
    least: np.ndarray
    greatest: np.ndarray
    hi: np.ndarray

    @staticmethod
    def of(shard: Shard) -> Entries:
        order = np.lexsort((shard.ids, shard.lo))
        hi, n = shard.hi[order], len(order)
        least, greatest = np.zeros(n, np.int64), np.zeros(n, np.int64)
        for i in range(n - 1, -1, -1):
            best = least[i + 1] if i + 1 < n else -1
            least[i] = order[i] if best < 0 or (hi[i], shard.ids[order[i]]) < (shard.hi[best], shard.ids[best]) else best
        for i in range(n):
            best = greatest[i - 1] if i else -1
            greatest[i] = order[i] if best < 0 or (-hi[i], shard.ids[order[i]]) < (-shard.hi[best], shard.ids[best]) else best
        return Entries(shard.lo[order], least, greatest, shard.hi)

    def find(self, mode: str, ql: float, qr: float) -> int:
        """An object that is valid for the query, or -1 if there is none; two binary searches."""
        n = len(self.lo)
        if not n:
            return -1
        if mode == "any":
            return int(self.least[0])
        if mode == "within":
            i = int(np.searchsorted(self.lo, ql, "left"))
            return int(self.least[i]) if i < n and self.hi[self.least[i]] <= qr else -1
        i = int(np.searchsorted(self.lo, ql, "right")) - 1
        return int(self.greatest[i]) if i >= 0 and self.hi[self.greatest[i]] >= qr else -1


@dataclass
class Adjacency:
    """Neighbours of every object in one array, with their bits."""

    begin: np.ndarray
    dst: np.ndarray
    bits: np.ndarray
    walks: dict = field(default_factory=dict, repr=False)  # what whole walks without a filter have reached, by their starts

    @staticmethod
    def of(n: int, src: np.ndarray, dst: np.ndarray, bits: np.ndarray) -> Adjacency:
        order = np.argsort(src, kind="stable")
        return Adjacency(np.searchsorted(src[order], np.arange(n + 1)), dst[order], bits[order])


def _reached(n: int, graph: Adjacency, starts: list[int], bit: int, ok: np.ndarray | None) -> tuple[np.ndarray, int]:
    """All objects that a walk from the starts enters, and the edges that it sees."""
    seen = np.zeros(n, bool)
    level = np.unique(np.array(starts, np.int64))
    levels, edges = [], 0
    while len(level):
        seen[level] = True
        levels.append(level)
        begin, many = graph.begin[level], graph.begin[level + 1] - graph.begin[level]
        total = int(many.sum())
        edges += total
        spot = np.arange(total) + np.repeat(begin - (np.cumsum(many) - many), many)
        near = graph.dst[spot]
        near = near[(graph.bits[spot] & bit > 0) & ~seen[near]]
        met = np.zeros(n, bool)
        met[near] = True
        level = np.flatnonzero(met)
        if ok is not None:
            level = level[ok[level]]
    return np.concatenate(levels), edges


def _walk(shard: Shard, graph: Adjacency, starts: list[int], q: np.ndarray, bit: int, ok: np.ndarray | None, returns: np.ndarray | None) -> tuple[list[int], dict]:
    """A beam that holds every object leaves none out, so the order of the walk does not matter: it goes level by level."""
    key = (bit, *starts)
    if ok is None and key in graph.walks:
        of, edges = graph.walks[key]
    else:
        of, edges = _reached(len(shard.ids), graph, starts, bit, ok)
        if ok is None and len(graph.walks) < 64:
            graph.walks[key] = of, edges
    diff = shard.x[of] - q
    d = np.einsum("ij,ij->i", diff, diff)
    effort = {"hops": len(of), "edges": edges, "distances": len(of)}
    if returns is not None:
        back = returns[of]
        of, d = of[back], d[back]
    return of[np.lexsort((shard.ids[of], d))].tolist(), effort


def beam(shard: Shard, graph: Adjacency, starts: list[int], q: np.ndarray, ef: int, bit: int, ok: np.ndarray | None, visited: str = "push", returns: np.ndarray | None = None, hops: int = 1) -> tuple[list[int], dict]:
    """Best-first search with a beam of ``ef``; the found objects by distance, and the effort.

    Only objects in ``ok`` (all, if None) are entered; of those, only ones in ``returns`` come back. An edge counts
    if it has the bit. Visited marks are set when an object is entered ("push") or met by any edge ("touch").
    ``hops`` 2 looks through neighbours that are not ok at theirs.
    """
    effort = {"hops": 0, "edges": 0, "distances": 0}
    if not starts:
        return [], effort
    if ef >= len(shard.ids) and visited == "push" and hops == 1:
        return _walk(shard, graph, starts, q, bit, ok, returns)
    seen = np.zeros(len(shard.ids), bool)
    seen[starts] = True

    def distance(i: np.ndarray) -> np.ndarray:
        effort["distances"] += len(i)
        diff = shard.x[i] - q
        return np.einsum("ij,ij->i", diff, diff)

    ids = shard.ids
    frontier = [(d, int(ids[i]), i) for d, i in zip(distance(np.array(starts)).tolist(), starts, strict=True)]
    heapq.heapify(frontier)
    best = [(-d, -k, i) for d, k, i in frontier if returns is None or returns[i]]
    heapq.heapify(best)
    while frontier:
        d, _, u = heapq.heappop(frontier)
        if len(best) >= ef and d > -best[0][0]:
            break
        effort["hops"] += 1
        span = slice(graph.begin[u], graph.begin[u + 1])
        near, has = graph.dst[span], graph.bits[span] & bit > 0
        effort["edges"] += len(near)
        fresh = np.unique(near[has & ~seen[near]])
        if hops == 2 and ok is not None:
            through = near[has & ~ok[near]]
            if len(through):
                second = np.concatenate([graph.dst[graph.begin[w] : graph.begin[w + 1]] for w in through])
                effort["edges"] += len(second)
                fresh = np.unique(np.concatenate([fresh, second[~seen[second]]]))
        if visited == "touch":
            seen[near] = True
        if ok is not None:
            fresh = fresh[ok[fresh]]
        if not len(fresh):
            continue
        seen[fresh] = True
        for dv, v in zip(distance(fresh).tolist(), fresh.tolist(), strict=True):
            key = int(ids[v])
            if len(best) < ef or (dv, key) < (-best[0][0], -best[0][1]):
                heapq.heappush(frontier, (dv, key, v))
                if returns is None or returns[v]:
                    heapq.heappush(best, (-dv, -key, v))
                    if len(best) > ef:
                        heapq.heappop(best)
    return [i for _, _, i in sorted((-d, -k, i) for d, k, i in best)], effort
