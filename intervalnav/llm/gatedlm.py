"""Gated recurrent language model over words, with class-factored output, trained and run in numpy.

Counts: every word of every training row, by 64-bit word hash, plus one end for each row. The ``vocabulary``
most frequent words (with the end and one entry for all others) are the network's; another word is
P(other) times its add-one share among the others, from the whole corpus' counts, so a text's probability is
proper. The counts of the ``head`` most frequent words are broadcast; the rest, which grow with the corpus,
meet the texts in a join.

Network: gates from the word's row and the state; P(word) = P(class) * P(word | class), classes being runs of
the frequency order. Training is truncated backpropagation over windows of ``window`` steps, with the state
carried on; a first pass over a bounded sample of rows gives a start, then trainers (at most ``trainers``)
go through all training rows (a lesser ``share`` can be asked for) and their weights are averaged by the tokens they saw.
Scoring carries each text's state from window to window to its end.

Defined cases: null texts count as empty and have only their end; without training rows all words are
unknown and the network is uniform; repeated rows are scored alike; long texts are scored whole.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import arrowtext as at
from .common import written

END, OTHER = 0, 1


@dataclass(frozen=True)
class Params:
    vocabulary: int = 1000
    head: int = 100_000
    classes: int = 32
    hidden: int = 16
    window: int = 16
    lanes: int = 48
    start_rows: int = 1500  # bound of the sample of the first pass
    share: float = 1.0  # of the training rows in the second pass: all
    least_rows: int = 1500  # in the second pass, while there are so many
    trainers: int = 128
    rate: float = 0.01
    seed: int = 11


def tokens(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of every row one after another, and the row offsets."""
    data, offs = at.string_buffers(pc.ascii_lower(column.fill_null("") if column.null_count else column))
    starts, ends, rows = at.words(data, offs)
    return at.span_hashes(data, starts, ends), np.concatenate([[0], np.cumsum(np.bincount(rows, minlength=len(offs) - 1))])


def counts(docs: DataFrame, text: str = "text") -> DataFrame:
    """(h, c): count of every word of the rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "t", 4 << 20):
                h, c = np.unique(tokens(part.column("t"))[0], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(c)], names=["h", "c"])

    return docs.select(F.col(text).alias("t")).mapInArrow(run, "h long, c long").groupBy("h").agg(F.sum("c").alias("c"))


@dataclass
class Lexicon:
    """The head's hashes (ascending) with counts and network entries, and the corpus totals."""

    hashes: np.ndarray
    count: np.ndarray
    entry: np.ndarray
    entry_count: np.ndarray
    n: int
    v: int
    rows: int
    other_total: int  # the others' tokens, distinct words, and one for unseen ones

    @staticmethod
    def of(table: DataFrame, rows: int, p: Params) -> Lexicon:
        total = table.agg(F.sum("c"), F.count("*")).first()
        top = table.orderBy(F.desc("c"), "h").limit(p.head).toArrow()  # at most ``head`` rows
        h, c = top.column("h").to_numpy().view(np.uint64), top.column("c").to_numpy()
        own = np.arange(len(h)) < p.vocabulary - 2
        words, n_words = int(total[0] or 0), int(total[1])
        others = words - int(c[own].sum())
        entry_count = np.concatenate([[rows, others], c[own]])
        entry = np.where(own, np.arange(len(h)) + 2, OTHER)
        order = np.argsort(h)
        return Lexicon(h[order], c[order], entry[order], entry_count, words + rows, n_words + (rows > 0), rows, others + n_words - int(own.sum()) + 1)

    def find(self, h: np.ndarray) -> np.ndarray:
        """Places in the head, or -1."""
        if not len(self.hashes) or not len(h):
            return np.full(len(h), -1)
        spot = np.minimum(np.searchsorted(self.hashes, h), len(self.hashes) - 1)
        return np.where(self.hashes[spot] == h, spot, -1)


class Network:
    """Weights in one float32 vector, with views by name."""

    def __init__(self, entry_count: np.ndarray, p: Params, flat: np.ndarray | None = None):
        v, h = len(entry_count), p.hidden
        order = np.argsort(-entry_count, kind="stable")
        self.rank = np.empty(v, np.int64)  # entries in the order of frequency
        self.rank[order] = np.arange(v)
        weight = np.sqrt(entry_count[order] + 1.0)
        cls = np.minimum((np.cumsum(weight) - weight) / weight.sum() * p.classes, p.classes - 1).astype(np.int64)
        _, cls = np.unique(cls, return_inverse=True)
        self.class_of = cls
        n = int(cls.max()) + 1
        self.begin = np.searchsorted(cls, np.arange(n + 1))
        shapes = {"e": (v, 3 * h), "u": (h, 3 * h), "b": (3 * h,), "c": (n, h), "cb": (n,), "w": (v, h), "wb": (v,)}
        size = sum(int(np.prod(s)) for s in shapes.values())
        if flat is None:
            flat = (np.random.default_rng(p.seed).standard_normal(size) * 0.1).astype(np.float32)
        self.flat, at_ = flat, 0
        for name, shape in shapes.items():
            k = int(np.prod(shape))
            setattr(self, name, flat[at_ : at_ + k].reshape(shape))
            at_ += k
        self.shapes = shapes

    def start(self) -> None:
        """Biases from the frequencies are learned quickly; only the gates' start is set."""
        self.b[: len(self.b) // 3] = 1.0

    def like(self) -> Network:
        out = object.__new__(Network)
        out.__dict__.update(self.__dict__)
        out.flat, at_ = np.zeros_like(self.flat), 0
        for name, shape in self.shapes.items():
            k = int(np.prod(shape))
            setattr(out, name, out.flat[at_ : at_ + k].reshape(shape))
            at_ += k
        return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return np.tanh(x * np.float32(0.5)) * np.float32(0.5) + np.float32(0.5)


def _output(net: Network, h: np.ndarray, y: np.ndarray, grad: Network | None = None) -> tuple[np.ndarray, np.ndarray | None]:
    """Natural log-probability of every target; with ``grad`` also the slope at h (summed loss)."""
    c = net.class_of[y]
    logits = h @ net.c.T + net.cb
    logits -= logits.max(1, keepdims=True)
    p = np.exp(logits)
    total = p.sum(1)
    rows = np.arange(len(y))
    out = logits[rows, c] - np.log(total)
    dh = None
    if grad is not None:
        p /= total[:, None]
        p[rows, c] -= 1
        dh = p @ net.c
        grad.c += p.T @ h
        grad.cb += p.sum(0)
    order = np.argsort(c, kind="stable")
    bounds = np.searchsorted(c[order], np.arange(len(net.begin)))
    for k in range(len(net.begin) - 1):
        of = order[bounds[k] : bounds[k + 1]]
        a, b = net.begin[k], net.begin[k + 1]
        if not len(of) or b - a == 1:
            continue
        hk = h[of]
        logits = hk @ net.w[a:b].T + net.wb[a:b]
        logits -= logits.max(1, keepdims=True)
        p = np.exp(logits)
        total = p.sum(1)
        i, t = np.arange(len(of)), y[of] - a
        out[of] += logits[i, t] - np.log(total)
        if grad is not None:
            p /= total[:, None]
            p[i, t] -= 1
            dh[of] += p @ net.w[a:b]
            grad.w[a:b] += p.T @ hk
            grad.wb[a:b] += p.sum(0)
    return out, dh


def _steps(net: Network, x: np.ndarray, h: np.ndarray, keep: list | None = None) -> np.ndarray:
    """States after every step for inputs (lanes, steps)."""
    n = net.u.shape[0]
    states = np.empty((x.shape[1], len(h), n), np.float32)
    for t in range(x.shape[1]):
        a, g = net.e[x[:, t]] + net.b, h @ net.u
        zr = _sigmoid(a[:, : 2 * n] + g[:, : 2 * n])
        z, r = zr[:, :n], zr[:, n:]
        m = np.tanh(a[:, 2 * n :] + r * g[:, 2 * n :])
        new = m + z * (h - m)
        if keep is not None:
            keep.append((x[:, t], h, z, r, m, g[:, 2 * n :]))
        states[t] = h = new
    return states


def _lanes(rows: list[np.ndarray], rank: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Entries of rows, longest first, with an end before and after each: flat, begins, steps."""
    size = np.array([len(r) + 1 for r in rows], np.int64)
    flat = np.concatenate([np.append(END, np.append(r, END)) for r in rows]).astype(np.int64)
    return rank[flat], np.cumsum(size + 1) - size - 1, size


def train(net: Network, rows: list[np.ndarray], p: Params) -> int:
    """One pass over the rows (entries of each) in place; gives the tokens seen."""
    rng = np.random.default_rng(p.seed)
    rows = [rows[i] for i in np.argsort([-len(r) for r in rows], kind="stable")]
    groups = [rows[i : i + p.lanes] for i in range(0, len(rows), p.lanes)]
    one, two = np.zeros_like(net.flat), np.zeros_like(net.flat)
    updates = seen = 0
    n = p.hidden
    for gi in rng.permutation(len(groups)):
        flat, begin, size = _lanes(groups[gi], net.rank)
        h = np.zeros((len(size), n), np.float32)
        for t0 in range(0, int(size[0]), p.window):
            live = int((size > t0).sum())
            steps = min(p.window, int(size[0]) - t0)
            t = t0 + np.arange(steps)
            valid = t < size[:live, None]
            spot = begin[:live, None] + np.minimum(t, size[:live, None] - 1)
            x, y = flat[spot], flat[spot + 1]
            keep: list = []
            states = _steps(net, x, h[:live], keep)
            grad = net.like()
            mask = valid.T
            _, dh = _output(net, states[mask], y.T[mask], grad)
            full = np.zeros_like(states)
            full[mask] = dh
            back = np.zeros((live, n), np.float32)
            for s in range(steps - 1, -1, -1):
                xs, before, z, r, m, gm = keep[s]
                d = full[s] + back
                dm = d * (1 - z) * (1 - m * m)
                dz = d * (before - m) * z * (1 - z)
                dr = dm * gm * r * (1 - r)
                gates = np.concatenate([dz, dr, dm], 1)
                inner = np.concatenate([dz, dr, dm * r], 1)
                np.add.at(grad.e, xs, gates)
                grad.b += gates.sum(0)
                grad.u += before.T @ inner
                back = d * z + inner @ net.u.T
            tokens_now = int(mask.sum())
            g = grad.flat / np.float32(max(tokens_now, 1) ** 0.5)
            norm = float(np.sqrt((g * g).sum()))
            if norm > 5:
                g *= np.float32(5 / norm)
            updates += 1
            one += np.float32(0.1) * (g - one)
            two += np.float32(0.01) * (g * g - two)
            net.flat -= np.float32(p.rate) * (one / np.float32(1 - 0.9**updates)) / (np.sqrt(two / np.float32(1 - 0.99**updates)) + np.float32(1e-6))
            h = h.copy()
            h[:live] = states[-1]
            seen += tokens_now
    return seen


def likelihood(net: Network, entries: np.ndarray, offs: np.ndarray, p: Params) -> np.ndarray:
    """log10 probability of every row's entries and its end."""
    size = np.diff(offs)
    order = np.argsort(-size, kind="stable")
    flat, begin, steps = _lanes([entries[offs[i] : offs[i + 1]] for i in order], net.rank)
    out = np.zeros(len(size))
    h = np.zeros((len(size), p.hidden), np.float32)
    t0 = 0
    while t0 < int(steps[0]):
        live = int(np.searchsorted(-steps, -t0, "left"))
        width = min(max(p.window, (1 << 13) // live), int(steps[0]) - t0)
        t = t0 + np.arange(width)
        mask = (t < steps[:live, None]).T
        spot = begin[:live, None] + np.minimum(t, steps[:live, None] - 1)
        states = _steps(net, flat[spot], h[:live])
        got, _ = _output(net, states[mask], flat[spot + 1].T[mask])
        out[:live] += np.bincount(np.nonzero(mask)[1], weights=got, minlength=live)
        h[:live] = states[-1]
        t0 += width
    back = np.empty(len(size))
    back[order] = out
    return back / np.log(10)


def _trained(rows: DataFrame, parts: int, lexicon, net_flat: np.ndarray, p: Params) -> np.ndarray:
    """Weights after one pass of each of ``parts`` trainers over its rows, averaged."""
    shared = rows.sparkSession.sparkContext.broadcast((lexicon, net_flat))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lex, flat = shared.value
        net = Network(lex.entry_count, p, flat.copy())
        seen = 0
        for batch in batches:
            for part in at.blocks(batch, "t", 4 << 20):
                h, offs = tokens(part.column("t"))
                spot = lex.find(h)
                entries = np.where(spot < 0, OTHER, lex.entry[spot] if len(lex.entry) else OTHER)
                seen += train(net, [entries[a:b] for a, b in zip(offs[:-1], offs[1:], strict=True)], p)
        if seen:
            yield pa.RecordBatch.from_arrays([pa.array([seen]), pa.array([net.flat], pa.list_(pa.float32()))], names=["seen", "weights"])

    made = rows.repartition(parts, "k").mapInArrow(run, "seen long, weights array<float>")
    mean = made.select("seen", F.posexplode("weights")).groupBy("pos").agg((F.sum(F.col("col") * F.col("seen")) / F.sum("seen")).cast("float").alias("w"))
    got = mean.orderBy("pos").toArrow().column("w").to_numpy()  # as many rows as the network has weights
    return got.astype(np.float32) if len(got) else net_flat


def fit(train_docs: DataFrame, table: DataFrame, rows: int, key: str, text: str, p: Params) -> tuple[Lexicon, np.ndarray]:
    lexicon = Lexicon.of(table, rows, p)
    net = Network(lexicon.entry_count, p)
    net.start()
    if not rows:
        return lexicon, net.flat
    dealt = train_docs.select(F.col(key).alias("k"), F.col(text).alias("t")).withColumn("u", F.pmod(F.xxhash64(F.col("k").cast("string"), F.lit(6)), F.lit(1 << 24)) / (1 << 24))
    first = min(1.0, p.start_rows / rows)
    flat = _trained(dealt.where(F.col("u") < first), 1, lexicon, net.flat, p)
    share = min(1.0, max(p.share, p.least_rows / rows))
    parts = int(min(p.trainers, max(1, rows * share // p.least_rows)))
    flat = _trained(dealt.where(F.col("u") >= 1 - share), parts, lexicon, flat, p)
    return lexicon, flat


def score(docs: DataFrame, training: Column, key: str = "doc_id", text: str = "text", p: Params = Params()) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score and score of every row; ``training`` marks rows to learn from."""
    learned = docs.where(training)
    table = written(counts(learned, text), "lm-counts")
    rows = learned.count()
    lexicon, flat = fit(learned, table, rows, key, text, p)
    shared = docs.sparkSession.sparkContext.broadcast((lexicon, flat))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lex, weights = shared.value
        net = Network(lex.entry_count, p, weights)
        for batch in batches:
            for part in at.blocks(batch, "t", 3 << 20):
                h, offs = tokens(part.column("t"))
                spot = lex.find(h)
                inside = spot >= 0
                c = np.where(inside, lex.count[spot], 0) if len(lex.count) else np.zeros(len(h), np.int64)
                entries = np.where(inside, lex.entry[spot], OTHER) if len(lex.count) else np.full(len(h), OTHER)
                per = np.diff(offs)
                row = np.repeat(np.arange(len(per)), per)
                log_c = np.where(inside, np.log10(c + 1.0), 0)
                base = np.bincount(row, weights=log_c, minlength=len(per)) + np.log10(lex.rows + 1.0)
                model = likelihood(net, entries, offs, p) if len(per) else np.zeros(0)
                other = entries == OTHER
                model += np.bincount(row, weights=np.where(other, log_c - np.log10(lex.other_total), 0), minlength=len(per))
                known = np.bincount(row[inside], minlength=len(per)) + (lex.rows > 0)
                # Words that are not in the head wait for their counts.
                wait_h, wait_row = h[~inside], row[~inside]
                by = np.lexsort((wait_h, wait_row))
                wait_h, wait_row = wait_h[by], wait_row[by]
                first = np.flatnonzero(np.r_[True, (wait_h[1:] != wait_h[:-1]) | (wait_row[1:] != wait_row[:-1])]) if len(by) else np.zeros(0, np.int64)
                many = np.diff(np.append(first, len(by)))
                ends = np.concatenate([[0], np.cumsum(np.bincount(wait_row[first], minlength=len(per)))]).astype(np.int32)
                items = pa.StructArray.from_arrays([pa.array(wait_h[first].view(np.int64)), pa.array(many.astype(np.int32))], ["h", "m"])
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(per + 1), pa.array(known), pa.array(base), pa.array(model), pa.ListArray.from_arrays(pa.array(ends), items)], names=["doc_id", "n_tokens", "known", "base", "model", "wait"])

    source = docs.select(F.col(key).alias("doc_id"), F.col(text).alias("t"))
    fields = f"doc_id {source.schema['doc_id'].dataType.simpleString()}, n_tokens long, known long, base double, model double, wait array<struct<h: long, m: int>>"
    scored = written(source.mapInArrow(run, fields).withColumn("rid", F.monotonically_increasing_id()), "lm-scored")
    waiting = scored.select("rid", F.explode("wait").alias("x")).select("rid", "x.h", "x.m")
    least = int(lexicon.count.min()) if len(lexicon.count) == p.head else 0
    rest = table.where(F.col("c") <= least) if least else table.limit(0)
    met = waiting.join(rest, "h", "left")
    late = met.groupBy("rid").agg(F.sum(F.when(F.col("c").isNotNull(), F.col("m") * F.log10(F.col("c") + 1)).otherwise(0.0)).alias("late"), F.sum(F.when(F.col("c").isNotNull(), F.col("m")).otherwise(0)).alias("late_known"))
    joined = scored.drop("wait").join(late, "rid", "left")
    late_log = F.coalesce("late", F.lit(0.0))
    return joined.select(
        "doc_id", "n_tokens", (F.col("known") + F.coalesce("late_known", F.lit(0))).cast("long").alias("n_known"), F.lit(lexicon.n).cast("long").alias("train_tokens"),
        (F.col("base") + late_log - F.col("n_tokens") * F.lit(float(np.log10(lexicon.n + lexicon.v + 1)))).alias("base_score"),
        (F.col("model") + late_log).alias("score"),
    )
