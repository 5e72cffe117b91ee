"""Best-fit packing of token pieces by bin completion.

Pieces are packed by their length only, so the search works on the histogram of lengths (at most ``capacity``
entries, whatever the input). It fills a bin around the largest length left: among the undominated fillings,
found by branch and bound with best fit as the incumbent and pruned by the waste that a bin may still have,
the fullest is taken, as often as the counts allow. Pieces then take their places by rank among equal lengths.

Defined cases: a null text counts as empty, an empty text still has its closing id; repeated rows are packed
each on their own; equal lengths are placed in the order of (document, piece); no documents give no rows.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import arrowtext as at

NODES = 20_000
CACHE = 400_000  # words of a generation
LINE = 512  # words that are coded at once


class WordTokens:
    """Ids of the words of a text, with a memory of words already tokenised, bounded to two generations of them.

    The tokenizer drops white space and never joins two words, so a text's ids are those of its words.
    Words are known by 64-bit hashes.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.clear()

    def clear(self) -> None:
        self.keys = np.zeros(0, np.uint64)
        self.start = np.zeros(0, np.int64)
        self.size = np.zeros(0, np.int64)
        self.flat = np.zeros(0, np.uint32)
        self.old = self.keys, self.start, self.size, self.flat

    def whole(self, texts: list[str]) -> list[list[int]]:
        return [x.ids for x in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def each(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words one after another, and how many each has; words are coded by the line, which costs less."""
        lines = [words[i : i + LINE] for i in range(0, len(words), LINE)]
        flat, sizes = [], []
        for line, coded in zip(lines, self.tokenizer.encode_batch([" ".join(x) for x in lines], add_special_tokens=False), strict=True):
            ids, spans = np.array(coded.ids, np.uint32), np.fromiter(chain.from_iterable(coded.offsets), np.int64).reshape(-1, 2)
            length = np.fromiter(map(len, line), np.int64, len(line))
            end = np.cumsum(length + 1) - 1
            word = np.minimum(np.searchsorted(end, spans[:, 0], "right"), len(line) - 1)
            if ((spans[:, 0] < (end - length)[word]) | (spans[:, 1] > end[word]) | (spans[:, 0] >= spans[:, 1])).any() or (word[1:] < word[:-1]).any():
                alone = self.whole(line)  # an id that is not of one word's characters
                ids, size = np.array([i for x in alone for i in x], np.uint32), np.fromiter(map(len, alone), np.int64, len(alone))
            else:
                size = np.bincount(word, minlength=len(line))
            flat.append(ids)
            sizes.append(size)
        return np.concatenate(flat), np.concatenate(sizes)

    def _learn(self, keys: np.ndarray, flat: np.ndarray, size: np.ndarray) -> None:
        """Keys are ascending and not yet known."""
        at_ = np.searchsorted(self.keys, keys)
        start = len(self.flat) + np.cumsum(size) - size
        self.keys, self.start, self.size = np.insert(self.keys, at_, keys), np.insert(self.start, at_, start), np.insert(self.size, at_, size)
        self.flat = np.concatenate([self.flat, flat])

    @staticmethod
    def _missing(keys: np.ndarray, known: np.ndarray) -> np.ndarray:
        if not len(known):
            return np.ones(len(keys), bool)
        return known[np.minimum(np.searchsorted(known, keys), len(known) - 1)] != keys

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and the row offsets into them."""
        data, offs = at.string_buffers(column)
        starts, ends, rows = at.words(data, offs)
        hashes = at.span_hashes(data, starts, ends)
        unique, first, inverse = np.unique(hashes, return_index=True, return_inverse=True)
        if len(self.keys) + len(unique) > CACHE:
            old = self.keys, self.start, self.size, self.flat
            self.clear()
            self.old = old
        missing = np.flatnonzero(self._missing(unique, self.keys))
        if len(missing) and len(self.old[0]):
            keys, start, size, flat = self.old
            again = unique[missing[~self._missing(unique[missing], keys)]]
            slot = np.searchsorted(keys, again)
            self._learn(again, flat[at.ragged(start[slot], size[slot])], size[slot])
            missing = np.flatnonzero(self._missing(unique, self.keys))
        if len(missing):
            raw = data.tobytes()
            self._learn(unique[missing], *self.each([raw[starts[i] : ends[i]].decode() for i in first[missing]]))
        slot = np.searchsorted(self.keys, unique)[inverse]
        size = self.size[slot]
        flat = self.flat[at.ragged(self.start[slot], size)]
        per_row = np.bincount(rows, weights=size, minlength=len(offs) - 1).astype(np.int64)
        return flat, np.concatenate([[0], np.cumsum(per_row)])


_encoders: dict[str, WordTokens] = {}


def _encoder(path: str) -> WordTokens:
    if path not in _encoders:
        _encoders[path] = WordTokens(path)
    return _encoders[path]


def pieces(docs: DataFrame, tokenizer: str, capacity: int, key: str = "doc_id", text: str = "text", end_id: int = 0) -> DataFrame:
    """doc_id, piece, start, length and ids_crc32 of every document's pieces of at most ``capacity`` ids."""
    source = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("t"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(tokenizer)
        for batch in batches:
            for part in at.blocks(batch, "t"):
                flat, offs = encoder.encode(part.column("t"))
                out: list[tuple] = []
                for doc, a, b in zip(part.column("doc_id").to_pylist(), offs[:-1].tolist(), offs[1:].tolist(), strict=True):
                    ids = np.append(flat[a:b], np.uint32(end_id)).astype("<u4")
                    out.extend((doc, i, s, min(capacity, len(ids) - s), zlib.crc32(ids[s : s + capacity].tobytes())) for i, s in enumerate(range(0, len(ids), capacity)))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return source.mapInArrow(at.lean(run), "doc_id long, piece int, start long, length long, ids_crc32 long")


def fill(counts: np.ndarray, largest: int, capacity: int, allowed: int = 0, nodes: int = NODES) -> list[int]:
    """Lengths that go beside ``largest``: the best undominated filling found, best fit at the least.

    ``counts``: how many of each length are left besides ``largest``. The search ends at a filling that wastes no
    more than ``allowed``, or after ``nodes`` steps; subtrees that must waste as much as the incumbent are pruned.
    """
    free = capacity - largest
    best: list[int] = []
    room = free  # best fit: always the longest that fits
    for size in np.flatnonzero(counts[: free + 1])[::-1].tolist():
        n = min(int(counts[size]), room // size)
        best += [size] * n
        room -= n * size
    least, steps = room, 0
    if not least:
        return best
    order = np.flatnonzero(counts[: free + 1])[::-1].tolist()
    reach = np.cumsum((counts[order] * order)[::-1])[::-1].tolist() if order else []
    stack: list[tuple[int, int, tuple[int, ...]]] = [(0, free, ())]
    while stack and least > allowed and steps < nodes:
        i, room, chosen = stack.pop()
        steps += 1
        if room < least:
            # Undominated: no unused length between the smallest chosen one and that plus the waste fits in its place.
            if not chosen or not counts[chosen[-1] + 1 : chosen[-1] + room + 1].any() or room == 0:
                least, best = room, list(chosen)
        while i < len(order) and order[i] > room:
            i += 1
        if i == len(order) or room - reach[i] >= least:  # even all that is left wastes too much
            continue
        size = order[i]
        most = min(int(counts[size]), room // size)
        stack.extend((i + 1, room - n * size, chosen + (size,) * n) for n in range(most + 1) if room - n * size == 0 or i + 1 < len(order) or n == most)
    return best


def plan(histogram: dict[int, int], capacity: int) -> tuple[list[tuple[int, int, int, int, int, int]], int]:
    """Places for ranks: (length, first rank, end rank, first bin, each bin's number of them, offset); and the bins used."""
    counts = np.zeros(capacity + 1, np.int64)
    for length, n in histogram.items():
        counts[length] = n
    used = counts * 0
    places, bins = [], 0
    while counts.any():
        largest = int(np.flatnonzero(counts)[-1])
        counts[largest] -= 1
        beside = fill(counts, largest, capacity)
        counts[largest] += 1
        filling: dict[int, int] = {}
        for x in [largest, *beside]:
            filling[x] = filling.get(x, 0) + 1
        times = min(int(counts[x]) // n for x, n in filling.items())
        offset = 0
        for x, n in filling.items():
            places.append((x, int(used[x]), int(used[x]) + n * times, bins, n, offset))
            used[x] += n * times
            counts[x] -= n * times
            offset += n * x
        bins += times
    return places, bins


def pack(pieces_: DataFrame, capacity: int, rows_per_group: int = 100_000) -> DataFrame:
    """The pieces with sequence_id and offset. ``pieces_`` must be cheap to read again (a written table)."""
    spark = pieces_.sparkSession
    n = pieces_.count()
    groups = max(64, n // rows_per_group)
    salted = pieces_.withColumn("g", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(groups)).cast("int"))
    by_group = salted.groupBy("length", "g").agg(F.count("*").alias("n"))
    histogram = {int(x["length"]): int(x["n"]) for x in pieces_.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most ``capacity`` rows
    places, _ = plan(histogram, capacity)
    # Ranks: a running count over the groups of a length, and the place within the group.
    before = by_group.withColumn("before", F.sum("n").over(Window.partitionBy("length").orderBy("g").rowsBetween(Window.unboundedPreceding, -1)))
    ranked = salted.withColumn("r", F.row_number().over(Window.partitionBy("length", "g").orderBy("doc_id", "piece", "start", "ids_crc32")) - 1)
    ranked = ranked.join(before.select("length", "g", F.coalesce("before", F.lit(0)).alias("before")), ["length", "g"])
    ranked = ranked.withColumn("rank", F.col("r") + F.col("before"))
    # The plan has a few rows for each length: its size is bounded by the capacity.
    table = spark.createDataFrame(places, "length long, low long, high long, bin long, each long, at long")
    listed = F.broadcast(table.groupBy("length").agg(F.sort_array(F.collect_list(F.struct("low", "high", "bin", "each", "at"))).alias("places")))
    placed = ranked.join(listed, "length").withColumn("p", F.element_at(F.filter("places", lambda x: (x["low"] <= F.col("rank")) & (F.col("rank") < x["high"])), 1))
    q = F.col("rank") - F.col("p.low")
    return placed.select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        (F.col("p.bin") + F.floor(q / F.col("p.each"))).cast("long").alias("sequence_id"),
        (F.col("p.at") + q % F.col("p.each") * F.col("length")).cast("long").alias("offset"),
    )
