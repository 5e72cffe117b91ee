"""Language identification with bit-sliced Bloom filters over byte n-grams.

Every slot of the filter array holds a bit mask of languages (a word for every 63 of them). The AND of an n-gram's slots is the set of
languages whose filter contains it, so one probe answers for all languages. A text's score for a language
is the number of its n-grams in that language's filter, less the expected number of false positives.

Defined cases: a null text and a text without a letter give ``und`` and score 0; with no learned language
all texts give ``und``; equal scores go to the alphabetically first language; rows are judged one by one,
so repeated rows repeat their result; columns other than the named ones are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import arrowtext as at

WORD = 63  # languages in a mask's word

# Bytes that can belong to a letter: ASCII letters and all bytes of longer UTF-8 sequences.
_LETTER = np.zeros(256, bool)
_LETTER[ord("a") : ord("z") + 1] = True
_LETTER[0x80:] = True


@dataclass(frozen=True)
class Params:
    """``per_language`` bounds the labelled rows that are learned from, in expectation and per language."""

    orders: tuple[int, ...] = (3, 5)
    per_language: int = 1500
    slots: int = 1 << 20
    probes: int = 3
    least_count: int = 3
    least_share: float = 0.2


@dataclass(frozen=True)
class Model:
    """``masks``: a word a slot for the first 63 languages; ``more``: further words, a row for every 63 languages."""

    languages: list[str]
    masks: np.ndarray
    false_rate: np.ndarray
    params: Params = field(default_factory=Params)
    more: np.ndarray = field(default_factory=lambda: np.zeros((0, 0), np.uint64))


def grams(column: pa.Array, orders: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the n-grams of letters, with word edges as spaces, and their row numbers."""
    data, offs = at.string_buffers(pc.utf8_lower(column.fill_null("") if column.null_count else column))
    size = np.diff(offs)
    # Every row is put between two spaces; then no n-gram reaches into another row.
    clean = np.full(len(data) + 2 * len(size), 32, np.uint8)
    row = np.repeat(np.arange(len(size)), size)
    clean[np.arange(len(data)) + 2 * row + 1] = np.where(_LETTER[data], data, 32)
    keep = np.ones(len(clean), bool)
    keep[1:] = (clean[1:] != 32) | (clean[:-1] != 32)
    owner = np.repeat(np.arange(len(size)), size + 2)
    keep[1:] |= owner[1:] != owner[:-1]
    clean, owner = clean[keep], owner[keep]
    codes, rows = [], []
    for n in orders:
        if len(clean) < n:
            continue
        code = np.zeros(len(clean) - n + 1, np.uint64)
        inner = np.zeros(len(code), bool)
        for i in range(n):
            part = clean[i : len(code) + i]
            code = (code << np.uint64(8)) | part
            if 0 < i < n - 1:
                inner |= part == 32
        fits = ~inner & (owner[n - 1 :] == owner[: len(code)])
        codes.append(code[fits] | np.uint64(n << 56))
        rows.append(owner[: len(code)][fits])
    if not codes:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate(codes), np.concatenate(rows)


def slots_of(codes: np.ndarray, probes: int, slots: int) -> Iterator[np.ndarray]:
    h = at.mix(codes)
    low, high = h & np.uint64(0xFFFFFFFF), h >> np.uint64(32)
    for i in range(probes):
        yield (low + np.uint64(i) * (high | np.uint64(1))) & np.uint64(slots - 1)


def learn(labelled: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id", params: Params = Params()) -> Model:
    """Filters from a bounded sample of labelled rows: about ``per_language`` rows of each language, by key hash."""
    rows = labelled.select(F.col(key).alias("k"), F.col(text).alias("t"), F.col(lang).alias("l")).where("l is not null and t is not null")
    sizes = dict(rows.groupBy("l").count().collect())  # a row for each language
    languages = sorted(sizes)
    if not languages:
        return Model([], np.zeros(params.slots, np.uint64), np.zeros(0), params)
    share = F.create_map(*[F.lit(x) for name in languages for x in (name, min(1.0, params.per_language / sizes[name]))])
    number = F.create_map(*[F.lit(x) for i, name in enumerate(languages) for x in (name, i)])
    sample = rows.where(F.col("l").isin(languages)).where(F.pmod(F.xxhash64(F.col("k").cast("string")), F.lit(1 << 20)) < share[F.col("l")] * (1 << 20))
    orders = params.orders

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "t", 2 << 20):
                codes, owner = grams(part.column("t"), orders)
                lang_of = part.column("n").to_numpy()[owner]
                order = np.lexsort((codes, lang_of))
                codes, lang_of = codes[order], lang_of[order]
                first = np.ones(len(codes), bool)
                first[1:] = (codes[1:] != codes[:-1]) | (lang_of[1:] != lang_of[:-1])
                where = np.flatnonzero(first)
                n = np.diff(np.append(where, len(codes)))
                yield pa.RecordBatch.from_arrays([pa.array(lang_of[where].astype(np.int32)), pa.array(codes[where].view(np.int64)), pa.array(n)], ["n", "g", "c"])

    counted = sample.select(number[F.col("l")].cast("int").alias("n"), "t").mapInArrow(at.lean(count), "n int, g long, c long").groupBy("n", "g").agg(F.sum("c").alias("c"))
    totals = F.broadcast(counted.groupBy("n").agg(F.sum("c").alias("total")))  # a row for each language
    rated = counted.join(totals, "n").withColumn("rate", F.col("c") / F.col("total"))
    # An n-gram is a language's own if frequent enough there next to the language that has it most.
    best = rated.groupBy("g").agg(F.max("rate").alias("best"), F.collect_list(F.struct("n", "c", "rate")).alias("of"))
    own = F.filter("of", lambda x: (x["rate"] >= F.col("best") * params.least_share) & (x["c"] >= params.least_count))
    held = best.select("g", F.explode(own).alias("x")).select("g", F.expr(f"x.n div {WORD}").cast("int").alias("w"), F.call_function("shiftleft", F.lit(1).cast("long"), F.col("x.n") % WORD).alias("m"))
    held = held.groupBy("g", "w").agg(F.bit_or("m").alias("m"))
    probes, slots = params.probes, params.slots

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes, w, m = batch.column("g").to_numpy().view(np.uint64), batch.column("w"), batch.column("m")
            for slot in slots_of(codes, probes, slots):
                yield pa.RecordBatch.from_arrays([pa.array(slot.astype(np.int32)), w, m], ["slot", "w", "m"])

    filled = held.mapInArrow(place, "slot int, w int, m long").groupBy("slot", "w").agg(F.bit_or("m").alias("m"))
    masks = np.zeros((-(-len(languages) // WORD), slots), np.uint64)
    got = filled.toArrow()  # at most ``slots`` rows for every 63 languages
    masks[got.column("w").to_numpy(), got.column("slot").to_numpy()] = got.column("m").to_numpy().view(np.uint64)
    fill = np.array([((masks[i // WORD] >> np.uint64(i % WORD)) & np.uint64(1)).mean() for i in range(len(languages))])
    return Model(languages, masks[0], fill**probes, params, masks[1:])


def judge(model: Model, column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Language number (-1: none), score and share of known n-grams for every row."""
    rows, n_lang, p = len(column), len(model.languages), model.params
    codes, owner = grams(column, p.orders)
    has_letter = np.asarray(pc.match_substring_regex(column, r"\pL").fill_null(False).to_numpy(zero_copy_only=False), bool)
    if not n_lang or not rows:
        return np.full(rows, -1), np.zeros(rows), np.zeros(rows)
    total = np.bincount(owner, minlength=rows)
    hits = np.zeros((rows, n_lang))
    places = list(slots_of(codes, p.probes, p.slots))
    for word, masks in enumerate([model.masks, *model.more]):
        held = masks[places[0]]
        for slot in places[1:]:
            held &= masks[slot]
        for i in range(word * WORD, min(n_lang, (word + 1) * WORD)):
            hits[:, i] = np.bincount(owner[(held >> np.uint64(i % WORD)) & np.uint64(1) != 0], minlength=rows)
    fixed = np.maximum(0, (hits - total[:, None] * model.false_rate) / (1 - np.minimum(model.false_rate, 0.99)))
    best = fixed.argmax(1)
    top = fixed[np.arange(rows), best]
    score = np.where(top > 0, top / np.maximum(fixed.sum(1), 1e-300), 0)
    known = top / np.maximum(total, 1)
    best = np.where(has_letter, best, -1)
    return best, np.clip(np.where(has_letter, score, 0), 0, 1), np.clip(np.where(has_letter, known, 0), 0, 1)


def identify(docs: DataFrame, model: Model, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns, lang_pred, score and known_share (of n-grams, in the chosen language) for every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # params.slots 8-byte masks
    source = docs.select(*keep, F.col(text).alias("__text"))
    schema = source.drop("__text").schema.add("lang_pred", "string").add("score", "double").add("known_share", "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        names = np.array([*m.languages, "und"], object)
        for batch in batches:
            for part in at.blocks(batch, "__text", 1 << 18):
                best, score, known = judge(m, part.column("__text"))
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(names[best].tolist(), pa.string()), pa.array(score), pa.array(known)], names=[*keep, "lang_pred", "score", "known_share"])

    return source.mapInArrow(at.lean(run), schema)
