"""Exact Jaccard join of n-gram sets by a prefix tree.

1. Every text becomes the sorted set of the hashes of its n-grams; equal sets are one node from here on.
2. Candidates: two sets that link differ in at most d n-grams, so of d + 1 + e segments (by n-gram hash) e + 1
   are equal in both, and one of these is not empty if one of the sets has at most e empty segments. Segments
   are made for classes of sizes, and a set also takes part in the next class if it may link there. A set with
   more than e empty segments also takes part in further divisions of its class, until it has fewer; so two
   sets that agree only in empty segments meet in a later division.
3. Sets that share a segment with another one are candidates; two sets that link share one.
4. Every set has a sketch: the parity of its hashes in each of as many buckets as it has members, about. The buckets
   in which two sketches differ are at most the n-grams in which the sets differ, so sketches refute pairs that
   cannot link, and only sets with a pair left have their texts moved.
5. Sets are compared in prefix trees: the sorted sets of a group are stored in a trie with edges of
   ``STEP`` n-grams; a probe walks all live nodes of a level at once, each node's overlap is computed once for
   all sets below it, and a subtree ends where what is left of the probe and of its sets cannot reach the
   needed overlap. First every set meets its best pivot, in blocks; then, where the sets of one segment are not yet
   one component, they meet by tiles of sets with one best pivot, one tile against a block of others.

Defined cases: a null, empty or blank text has the empty set and links with nothing; a text with fewer words
than n has its whole word sequence as its one n-gram; repeated rows of one id share their component; columns
other than the two named are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import arrowtext as at
from .common import marked, swept, written
from .components import HELD, connected

STEP = 64
SEGMENTED = 80  # least percentage that finds its candidates by segments
SAMPLED, COMMON = 2_000_000, 200_000  # n-grams that are counted for the order of rarity, and those it keeps
MINOR, MAJOR = 64, 192  # sets in a tile of the last comparison; in a block of the first, or that a tile meets at once
_SALT = np.uint64(0x5851F42D4C957F2D)


def sets_of(column: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-gram hashes of every row, ascending, and the row offsets (rows + 1)."""
    data, offs = at.string_buffers(pc.ascii_lower(column.fill_null("") if column.null_count else column))
    starts, ends, rows = at.words(data, offs)
    h = at.span_hashes(data, starts, ends)
    per = np.bincount(rows, minlength=len(offs) - 1)
    code = np.zeros(len(h), np.uint64)
    width = np.minimum(per, n)[rows] if len(rows) else per[:0]
    for i in range(n):
        has = np.flatnonzero(width > i)
        has = has[has + i < len(h)]
        code[has] = at.mix(code[has] * np.uint64(0x2545F4914F6CDD1D) + h[has + i] + np.uint64(i + 1))
    last = np.cumsum(per)[rows] if len(rows) else per[:0]
    fits = np.arange(len(h)) + width <= last
    code, rows = code[fits], rows[fits]
    order = np.argsort(code)
    by_row = rows[order].astype(np.uint16) if len(offs) < 1 << 16 else rows[order]  # 16 bits are sorted by digits
    order = order[np.argsort(by_row, kind="stable")]
    code, rows = code[order], rows[order]
    keep = np.ones(len(code), bool)
    keep[1:] = (code[1:] != code[:-1]) | (rows[1:] != rows[:-1])
    code, rows = code[keep], rows[keep]
    return code, np.concatenate([[0], np.cumsum(np.bincount(rows, minlength=len(offs) - 1))])


def set_ids(code: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """One id for equal sets, from two sums over the members; 0 for the empty set."""
    size = np.diff(offs)
    out = np.zeros(len(size), np.uint64)
    full = size > 0
    if full.any():
        begins = offs[:-1][full]
        a, b = np.add.reduceat(at.mix(code ^ _SALT), begins), np.bitwise_xor.reduceat(at.mix(code + _SALT), begins)
        out[full] = at.mix(a ^ at.mix(b + size[full].astype(np.uint64)))
    return out.view(np.int64)


def sketches(code: np.ndarray, offs: np.ndarray) -> list[bytes]:
    """The parity of every row's hashes by their low bits, in 64 buckets or the next power of two from its size."""
    size = np.diff(offs)
    wide = np.int64(1) << np.ceil(np.log2(np.maximum(size, 64))).astype(np.int64)
    ends = np.cumsum(wide)
    base = np.repeat(ends - wide, size)
    bucket = base + (code & np.repeat(wide - 1, size).astype(np.uint64)).astype(np.int64)
    parity = np.bincount(bucket, minlength=int(ends[-1]) if len(ends) else 0) & 1
    raw = np.packbits(parity.astype(np.uint8), bitorder="little").tobytes()
    return [raw[a // 8 : b // 8] for a, b in zip((ends - wide).tolist(), ends.tolist(), strict=True)]


def unrefuted(size: np.ndarray, root: np.ndarray, side: np.ndarray | None, bits: list[bytes], percent: int) -> np.ndarray:
    """Whether a set may link with another of a different root (and of the other side, 0 and 1): exact, since sketches
    of two sets differ in at most as many buckets as the sets in members."""
    out = np.zeros(len(size), bool)
    width = np.array([len(b) // 8 for b in bits], np.int64)
    words = {w: np.frombuffer(b"".join(b for b in bits if len(b) == 8 * w), np.uint64).reshape(-1, w) for w in np.unique(width).tolist()}
    of = {w: np.flatnonzero(width == w) for w in words}

    def folded(x: np.ndarray, w: int) -> np.ndarray:
        while x.shape[1] > w:
            x = x[:, : x.shape[1] // 2] ^ x[:, x.shape[1] // 2 :]
        return x

    for wa in words:
        for wb in words:
            if side is None and wb < wa:
                continue
            a, b = (of[wa], of[wb]) if side is None else (of[wa][side[of[wa]] == 0], of[wb][side[of[wb]] == 1])
            if not len(a) or not len(b) or size[a].max() * 100 < percent * size[b].min() or size[b].max() * 100 < percent * size[a].min():
                continue
            w = min(wa, wb)
            x, y = (folded(words[v][np.searchsorted(of[v], i)], w) for v, i in ((wa, a), (wb, b)))
            step = max(1, (1 << 18) // (len(b) * w))
            for i in range(0, len(a), step):
                some = a[i : i + step]
                apart = np.maximum(np.bitwise_count(x[i : i + step, None, :] ^ y[None, :, :]).sum(2, dtype=np.int64), np.abs(size[some][:, None] - size[b][None, :]))
                may = (apart * (100 + percent) <= (size[some][:, None] + size[b][None, :]) * (100 - percent)) & (root[some][:, None] != root[b][None, :])
                out[some[may.any(1)]] = True
                out[b[may.any(0)]] = True
    return out


class Classes:
    """Size classes, their number of segments, and who takes part where.

    Segments get smaller with the percentage; narrower classes then keep them from being empty too often.
    """

    def __init__(self, percent: int):
        self.percent = percent
        self.ratio, self.spare = (0.7, 16) if percent >= 90 else (0.8, 9)  # between the sizes of two classes; a segment to spare for so many

    def of(self, size: np.ndarray) -> np.ndarray:
        return np.floor(np.log(np.maximum(size, 1)) / -np.log(self.ratio) + 1e-9).astype(np.int64)

    def largest(self, c: np.ndarray) -> np.ndarray:
        return np.ceil(self.ratio ** -(c.astype(float) + 1) + 1e-6).astype(np.int64)

    def segments(self, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """How many, and how many of them may be empty in a set whose links all share a full one."""
        p = self.percent  # |A ^ B| * (100 + p) <= (|A| + |B|) * (100 - p)
        apart = 2 * self.largest(c) * (100 - p) // (100 + p)
        return apart + 1 + apart // self.spare, apart // self.spare

    def partner(self, size: np.ndarray) -> np.ndarray:
        """Class of the largest set that can link with one of this size."""
        return self.of(size * 100 // self.percent)


def signatures(code: np.ndarray, offs: np.ndarray, classes: Classes) -> tuple[np.ndarray, np.ndarray]:
    """Segment signatures and the row of each."""
    size = np.diff(offs)
    rows = np.flatnonzero(size > 0)
    sigs, owners = [], []
    for step in range(int((classes.partner(size[rows]) - classes.of(size[rows])).max(initial=-1)) + 1):
        part = rows[classes.of(size[rows]) + step <= classes.partner(size[rows])]
        c = classes.of(size[part]) + step
        division = 0
        while len(part):
            m, spare = classes.segments(c)
            base = np.cumsum(m) - m
            index = at.ragged(offs[part], size[part])
            slot = np.repeat(np.arange(len(part)), size[part])
            h = at.mix(code[index] + np.uint64(0x9E3779B97F4A7C15 * (division + 1) % 2**64))
            seg = (h >> np.uint64(32)) * m[slot].astype(np.uint64) >> np.uint64(32)
            place = base[slot] + seg.astype(np.int64)
            total = np.zeros(int(m.sum()), np.uint64)
            np.add.at(total, place, at.mix(h ^ _SALT))
            number = np.bincount(place, minlength=len(total))
            owner = np.repeat(np.arange(len(part)), m)
            seg_no = np.arange(len(total)) - base[owner]
            tag = (c[owner] * 1_000_003 + seg_no) * 4099 + division
            full = number > 0
            sigs.append(at.mix(total[full] ^ at.mix(tag[full].astype(np.uint64) ^ (number[full].astype(np.uint64) << np.uint64(48)))))
            owners.append(part[owner[full]])
            again = np.flatnonzero(np.bincount(owner[~full], minlength=len(part)) > spare)
            part, c = part[again], c[again]
            division += 1
    if not sigs:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate(sigs), np.concatenate(owners)


def rarest(code: np.ndarray, offs: np.ndarray, percent: int, common: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """The n-grams of every row of which a linked set shares one, and the row of each; ``common``: hashes (ascending), counts."""
    size = np.diff(offs)
    owner = np.repeat(np.arange(len(size)), size)
    count = np.zeros(len(code), np.int64)
    if len(common[0]) and len(code):
        spot = np.minimum(np.searchsorted(common[0], code), len(common[0]) - 1)
        count = np.where(common[0][spot] == code, common[1][spot], 0)
    order = np.lexsort((code, count, owner))
    many = np.where(size > 0, size + (-size * percent // 100) + 1, 0)
    first = np.arange(len(code)) - np.repeat(offs[:-1], size) < np.repeat(many, size)
    return code[order][first], owner[first]


class Trie:
    """Sorted sets in a prefix tree whose edges hold up to STEP members; sets can be taken out."""

    def __init__(self, sets: list[np.ndarray]):
        self.sets = sets
        self.size = np.array([len(s) for s in sets], np.int64)
        self.levels: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        self.node_of: list[np.ndarray] = []  # of every set on every level, -1 beyond its end
        parent_of = np.zeros(len(sets), np.int64)
        depth = 0
        while (self.size > depth).any():
            seen: dict[tuple[int, bytes], int] = {}
            node = np.full(len(sets), -1)
            edges, parents = [], []
            for i, s in enumerate(sets):
                if len(s) > depth:
                    edge = s[depth : depth + STEP]
                    key = (int(parent_of[i]), edge.tobytes())
                    if key not in seen:
                        seen[key] = len(seen)
                        edges.append(edge)
                        parents.append(key[0])
                    node[i] = seen[key]
            widths = np.array([len(e) for e in edges], np.int64)
            inside = node >= 0
            low, high = np.full(len(edges), 1 << 60), np.zeros(len(edges), np.int64)
            np.minimum.at(low, node[inside], self.size[inside])
            np.maximum.at(high, node[inside], self.size[inside])
            self.levels.append((np.concatenate(edges), np.cumsum(widths) - widths, widths, np.array(parents), low, high))
            self.node_of.append(node)
            parent_of = node
            depth += STEP
        self.left = [np.bincount(n[n >= 0], minlength=len(lv[1])) for n, lv in zip(self.node_of, self.levels, strict=True)]
        self.ends = [np.flatnonzero((self.size > d * STEP) & (self.size <= (d + 1) * STEP)) for d in range(len(self.levels))]
        self.present = np.ones(len(sets), bool)

    def remove(self, i: int) -> None:
        self.present[i] = False
        for node, left in zip(self.node_of, self.left, strict=True):
            if node[i] < 0:
                break
            left[node[i]] -= 1

    def links(self, x: np.ndarray, percent: int) -> np.ndarray:
        """Sets still present whose Jaccard similarity with x is at least the percentage."""
        found: list[int] = []
        n = len(x)
        overlap = np.zeros(1, np.int64)  # of the parents' paths
        alive = np.ones(1, bool)
        for d, (members, starts, widths, parents, low, high) in enumerate(self.levels):
            on = np.flatnonzero(alive[parents] & (self.left[d] > 0) & (low * percent <= n * 100) & (high * 100 >= n * percent))
            here = np.zeros(len(starts), np.int64)
            live = np.zeros(len(starts), bool)
            if not len(on):
                break
            edge = members[at.ragged(starts[on], widths[on])]
            spot = np.searchsorted(x, edge)
            hit = x[np.minimum(spot, n - 1)] == edge
            begins = np.cumsum(widths[on]) - widths[on]
            got = overlap[parents[on]] + np.add.reduceat(hit, begins, dtype=np.int64)
            here[on] = got
            # What is left: the probe's members after the edge's last one, and the longest set below.
            rest_x = n - np.searchsorted(x, edge[begins + widths[on] - 1], "right")
            rest_y = high[on] - d * STEP - widths[on]
            best = got + np.minimum(rest_x, rest_y)
            live[on] = best * (100 + percent) >= percent * (n + low[on])
            ended = self.ends[d]
            ended = ended[self.present[ended] & live[self.node_of[d][ended]]]
            both = here[self.node_of[d][ended]]
            found += ended[100 * both >= percent * (n + self.size[ended] - both)].tolist()
            overlap, alive = here, live
        return np.array(found, np.int64)


def forest(ids: np.ndarray, sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Links that connect all sets of the group that are connected by links."""
    trie = Trie(sets)
    out: list[tuple[int, int]] = []
    for root in range(len(ids)):
        if not trie.present[root]:
            continue
        trie.remove(root)
        queue = [root]
        while queue and trie.present.any():
            i = queue.pop()
            for j in trie.links(sets[i], percent).tolist():
                trie.remove(j)
                out.append((int(ids[i]), int(ids[j])))
                queue.append(j)
    return out


def across(left: tuple[np.ndarray, list[np.ndarray]], right: tuple[np.ndarray, list[np.ndarray]], percent: int) -> list[tuple[int, int]]:
    """Links between sets (ids, members) of two sides that connect all of them that are connected by links between the sides."""
    sides, tries = (left, right), (Trie(left[1]), Trie(right[1]))
    out: list[tuple[int, int]] = []
    for root in range(len(left[0])):
        if not tries[0].present[root]:
            continue
        tries[0].remove(root)
        queue = [(0, root)]
        while queue:
            side, i = queue.pop()
            if not tries[1 - side].present.any():
                continue
            for j in tries[1 - side].links(sides[side][1][i], percent).tolist():
                tries[1 - side].remove(j)
                out.append((int(sides[side][0][i]), int(sides[1 - side][0][j])))
                queue.append((1 - side, j))
    return out


def _open(groups: DataFrame, keys: list[str], percent: int, sides: bool = False) -> DataFrame:
    """The rows (g, side, s) of every group of (s, side, root, n, bits) whose sets the sketches leave a partner."""
    side = F.col("side") if sides else F.lit(0)
    dealt = groups.select(F.xxhash64(*keys).alias("g"), side.cast("int").alias("side"), "s", "root", "n", "bits").repartition("g").sortWithinPartitions("g")

    def solve(g: int, parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        own = pa.Table.from_batches(parts)
        size, root, at_side = (own.column(c).to_numpy() for c in ("n", "root", "side"))
        stay = np.flatnonzero(unrefuted(size, root, at_side if sides else None, own.column("bits").to_pylist(), percent))
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(stay), g)), pa.array(at_side[stay]), pa.array(own.column("s").to_numpy()[stay])], names=["g", "side", "s"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: list[pa.RecordBatch] = []
        now = None
        for batch in batches:
            g = batch.column("g").to_numpy()
            cuts = np.flatnonzero(np.r_[True, g[1:] != g[:-1]]) if len(g) else np.zeros(0, np.int64)
            for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(g)], strict=True):
                if g[a] != now and parts:
                    yield solve(now, parts)
                    parts = []
                now = int(g[a])
                parts.append(batch.slice(a, b - a))
        if parts:
            yield solve(now, parts)

    return dealt.mapInArrow(run, "g long, side int, s long")


def _compare(groups: DataFrame, keys: list[str], n: int, percent: int, sides: bool = False) -> DataFrame:
    """Links (u, v) found in every group of (s, t), or with ``sides`` between those of its two sides (s, side, t).

    Groups are small, and two that share a hash do no harm.
    """
    side = F.col("side") if sides else F.lit(0)
    dealt = groups.select(F.xxhash64(*keys).alias("g"), "s", side.cast("int").alias("side"), "t").repartition("g").sortWithinPartitions("g")

    def solve(ids: list[np.ndarray], of: list[np.ndarray], texts: list[pa.Array]) -> list[tuple[int, int]]:
        own: tuple[dict[int, np.ndarray], dict[int, np.ndarray]] = ({}, {})
        for i, at_side, column in zip(ids, of, texts, strict=True):
            code, offs = sets_of(column, n)
            for s, where, members in zip(i.tolist(), at_side.tolist(), np.split(code, offs[1:-1]), strict=True):
                own[where][s] = members
        both = [(np.array(list(x), np.int64), list(x.values())) for x in own]
        return across(*both, percent) if sides else forest(*both[0], percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, of, texts, now = [], [], [], None
        for batch in batches:
            g, s, at_side, column = *(batch.column(c).to_numpy() for c in ("g", "s", "side")), batch.column("t")
            cuts = np.flatnonzero(np.r_[True, g[1:] != g[:-1]]) if len(g) else np.zeros(0, np.int64)
            out: list[tuple[int, int]] = []
            for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(g)], strict=True):
                if g[a] != now and ids:
                    out += solve(ids, of, texts)
                    ids, of, texts = [], [], []
                now = g[a]
                ids.append(s[a:b].copy())
                of.append(at_side[a:b].copy())
                texts.append(column.slice(a, b - a))
            yield _pairs(out)
        if ids:
            yield _pairs(solve(ids, of, texts))

    return dealt.mapInArrow(at.lean(run), "u long, v long")


def _pairs(found: list[tuple[int, int]]) -> pa.RecordBatch:
    both = np.array(found, np.int64).reshape(-1, 2)
    return pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1])], names=["u", "v"])


def _of(source: DataFrame, wanted: DataFrame) -> DataFrame:
    """The texts (t) whose doc_id is wanted, those of repeated rows once; most others stay out of the shuffle."""
    likely = marked(source, "doc_id", wanted).where("__marked")
    # The keys of an equality that holds for nulls, as columns, so that texts are dealt out once for join and groups.
    id_, absent = F.coalesce("doc_id", F.lit(0)).alias("id"), F.isnull("doc_id").alias("absent")
    # An inner join, since the optimiser would put a semi join below the filter.
    met = likely.select(id_, absent, "t").join(wanted.select(id_, absent).distinct().hint("merge"), ["id", "absent"])
    return met.groupBy("id", "absent", F.xxhash64("t").alias("x")).agg(F.first("t").alias("t")).select("t")


def _common(sets: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Hashes (ascending) and counts of the n-grams that most of these (s, members) hold, if more than one does."""

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            h = np.frombuffer(b"".join(batch.column("members").to_pylist()), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(h)], names=["h"])

    top = sets.select("members").mapInArrow(spread, "h long").groupBy("h").agg(F.count("*").alias("c")).where("c > 1").orderBy(F.desc("c"), "h").limit(COMMON).toArrow()
    h, c = top.column("h").to_numpy().view(np.uint64), top.column("c").to_numpy()
    order = np.argsort(h)
    return h[order], c[order]


def _in_keys(held: DataFrame, label: DataFrame, best: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Rows (g, side, s) of the groups in which sets of different components that share a key (sig, s) meet, tile against tile.

    A tile holds up to about MINOR sets with one best pivot (p, s), which mostly share their keys, so that a key has few
    tiles even where it has many sets; two tiles meet once, whatever number of keys they share.
    """
    pivots = best.union(best.select("p", F.col("p").alias("s")).distinct())  # a pivot can have a better one itself
    pivots = pivots.groupBy("s").agg(F.max_by("p", F.col("p") != F.col("s")).alias("p"))
    many = pivots.groupBy("p").agg(F.ceil(F.count("*") / MINOR).alias("k"))
    tiles = pivots.join(many, "p").select("s", F.xxhash64("p", F.pmod(F.xxhash64("s", F.lit(7)), F.col("k"))).alias("tile"))
    known = sets.select("s", "n").join(label.select(F.col("u").alias("s"), "root"), "s", "left").withColumn("root", F.coalesce("root", "s")).join(tiles, "s")
    known = written(known.select("s", "n", "root", "tile"), "sets-known")
    dealt = held.select("sig", "s").join(known, "s").select("sig", "tile", "root", "n").repartition("sig")
    per = dealt.groupBy("sig", "tile").agg(F.min("root").alias("r0"), F.max("root").alias("r1"), F.min("n").alias("n0"), F.max("n").alias("n1"))
    by_sig = Window.partitionBy("sig")
    open_ = written(per.withColumns({"a": F.min("r0").over(by_sig), "b": F.max("r1").over(by_sig)}).where("a < b").drop("a", "b"), "sets-open")
    left, right = (open_.select("sig", *[F.col(c).alias(f"{c}{x}") for c in ("tile", "r0", "r1", "n0", "n1")]) for x in "ab")
    # Without those of which all sets are of one component, and those whose sizes are too far apart.
    pairs = left.join(right, "sig").where("tilea <= tileb and (r0a < r1a or r0b < r1b or r0a != r0b)")
    pairs = pairs.where(f"{percent} * n0a <= 100 * n1b and {percent} * n0b <= 100 * n1a").select("tilea", "tileb").distinct()
    pairs = written(pairs, "sets-pairs")
    counted = pairs.join(known.groupBy(F.col("tile").alias("tileb")).agg(F.count("*").alias("k")), "tileb")
    blocks = counted.groupBy("tilea").agg(F.ceil(F.sum("k") / MAJOR).alias("blocks"))
    dealt = pairs.join(blocks, "tilea").select("tilea", F.pmod(F.xxhash64("tileb", F.lit(7)), F.col("blocks")).alias("b"), F.col("tileb").alias("tile"), F.lit(1).alias("side"))
    dealt = dealt.union(dealt.select("tilea", "b", F.col("tilea").alias("tile"), F.lit(0).alias("side")).distinct())
    placed = dealt.join(known.select("tile", "s", "root"), "tile")
    return _open(placed.join(sets, "s"), ["tilea", "b"], percent, sides=True)


def components(docs: DataFrame, key: str = "doc_id", text: str = "text", n: int = 3, percent: int = 90) -> DataFrame:
    """doc_id, n_shingles and component_id of every row: the least id reachable by links of at least ``percent``."""
    source = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("t"))
    classes = Classes(percent)

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "t"):
                code, offs = sets_of(part.column("t"), n)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(np.diff(offs)), pa.array(set_ids(code, offs)), pa.array(sketches(code, offs), pa.binary())], names=["doc_id", "n", "s", "bits"])

    def members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "t"):
                code, offs = sets_of(part.column("t"), n)
                raw = code.tobytes()
                cut = [raw[8 * a : 8 * b] for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(set_ids(code, offs)), pa.array(cut, pa.binary())], names=["s", "members"])

    meta = written(source.mapInArrow(at.lean(describe), "doc_id long, n long, s long, bits binary"), "sets-meta")
    segmented = percent >= SEGMENTED
    common = None
    if not segmented:
        total = meta.agg(F.sum("n")).first()[0] or 0
        picked = meta.where(F.pmod(F.xxhash64("s"), F.lit(1 << 24)) < F.lit(int(min(1.0, SAMPLED / max(total, 1)) * (1 << 24)))).where("n > 0")
        picked = picked.groupBy("s").agg(F.min("doc_id").alias("doc_id")).select("doc_id")  # equal sets count once
        sets = source.join(F.broadcast(picked), "doc_id", "left_semi").select("t").mapInArrow(members, "s long, members binary").dropDuplicates(["s"])
        common = source.sparkSession.sparkContext.broadcast(_common(sets))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "t"):
                code, offs = sets_of(part.column("t"), n)
                ids = set_ids(code, offs)
                sigs, owner = signatures(code, offs, classes) if common is None else rarest(code, offs, percent, common.value)
                _, once = np.unique(ids, return_index=True)  # equal sets of this block sign once
                first = np.zeros(len(ids), bool)
                first[once] = True
                keep = first[owner]
                yield pa.RecordBatch.from_arrays([pa.array(sigs[keep].view(np.int64)), pa.array(ids[owner[keep]])], names=["sig", "s"])

    signed = source.mapInArrow(at.lean(sign), "sig long, s long")
    # One shuffle of the keys: those that only one set has go where they arrive. Sets of one key are alike (or share a
    # rare n-gram), so a key has few next to a task's keys.
    by_sig = Window.partitionBy("sig")
    held = signed.withColumns({"p": F.min("s").over(by_sig), "q": F.max("s").over(by_sig)}).where("p != q").select("sig", "s", "p")
    held = written(held.distinct(), "sets-held")
    votes = held.where("s != p").groupBy("p", "s").agg(F.count("*").alias("c"))
    votes = written(votes, "sets-votes")
    swept(docs.sparkSession)  # the keys are the largest shuffle
    # Of every candidate set one document and its sketch.
    firsts = meta.where("n > 0").groupBy("s").agg(F.min("doc_id").alias("doc_id"))
    candidates = held.select("s").distinct().hint("merge")
    sets = written(meta.where("n > 0").join(candidates, "s").groupBy("s").agg(F.min("doc_id").alias("doc_id"), F.first("n").alias("n"), F.first("bits").alias("bits")), "sets-sketched")
    firsts_of, sets = sets.select("s", "doc_id"), sets.select("s", "n", "bits")

    # Texts of the sets that have a partner left, from one document of each: shorter than the sets, which are made again where they meet.
    def named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "t"):
                yield pa.RecordBatch.from_arrays([pa.array(set_ids(*sets_of(part.column("t"), n))), part.column("t")], names=["s", "t"])

    def linked(groups: DataFrame, name: str, sides: bool = False) -> DataFrame:
        left = written(groups, f"{name}-left")
        texts = _of(source, firsts_of.join(left.select("s").distinct(), "s").select("doc_id"))
        stored = written(texts.mapInArrow(at.lean(named), "s long, t string"), f"{name}-texts")
        return written(_compare(left.join(stored, "s"), ["g"], n, percent, sides), name)

    # First comparison: every set with the pivot that it shares most segments with, in blocks.
    best = votes.groupBy("s").agg(F.max_by("p", F.struct("c", -F.col("p"))).alias("p")).select("p", "s")
    dealt = best.withColumn("b", F.row_number().over(Window.partitionBy("p", F.pmod(F.xxhash64("s"), F.lit(64))).orderBy("s")))
    dealt = dealt.withColumn("b", (F.pmod(F.xxhash64("s"), F.lit(64)) * F.lit(1 << 20) + F.floor(F.col("b") / MAJOR)).cast("long"))
    sizes = best.groupBy("p").agg(F.count("*").alias("k"))
    dealt = dealt.join(sizes, "p").withColumn("b", F.when(F.col("k") <= MAJOR, F.lit(0)).otherwise(F.col("b"))).select("p", "b", "s")
    dealt = dealt.union(dealt.select("p", "b", F.col("p").alias("s")).distinct())
    links = linked(_open(dealt.join(sets, "s").withColumn("root", F.col("s")), ["p", "b"], percent), "sets-links")
    swept(docs.sparkSession)
    label = connected(links, held=HELD)
    more = linked(_in_keys(held, label, best, sets, percent), "sets-more-links", sides=True)
    final = connected(written(links.union(more), "sets-all-links"), held=HELD)
    swept(docs.sparkSession)

    by_set = firsts.withColumnRenamed("doc_id", "first").join(final.withColumnRenamed("u", "s"), "s", "left").withColumn("root", F.coalesce("root", "s"))
    least = by_set.groupBy("root").agg(F.min("first").alias("component_id"))
    named = by_set.join(least, "root").select("s", "component_id")
    out = meta.where("n > 0").join(named, "s").select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    return out.union(meta.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id")))
