"""Document fingerprints by consistent weighted sampling, with DataFrame functions only.

A text is the bag of its word shingles; a shingle's weight is its count. For every shingle and sample, hashes give
two gamma variates and a uniform one; from these and the weight follow a level and a value, and the shingle with the
least value is the sample, named by the shingle and its level. The chance that two bags have the same sample is
their generalised Jaccard similarity: the sum of the lesser weights over the sum of the greater ones. All samples
are taken over the whole bag, so short texts have as many as long ones. A fingerprint is four hex digits a sample.

Defined cases: null texts count as empty; a text without words has an empty bag, whose fingerprint is all
zeros and which is like another empty one (1.0) and unlike any other (0.0); shorter texts than a shingle are
one shingle; the next document of the last one is the first; rows repeated under one id follow each other
in the order of their texts' hashes; a null id comes before all others.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written

BLOCK = 200  # ids in a block: what one task must hold together
SPAN = 4096  # blocks in a group when successors are looked up
GROUP = 8  # samples that are drawn together
CHARS = 3_000_000  # of text in a partition, about
REACH = 24.0  # a sample is empty, and so unlike any other, with a probability of exp(-REACH) = 4e-11


def shingles(text: Column, words: int) -> Column:
    """Hashes of the word shingles of a text; none for a text without words."""
    parts = F.split(F.trim(F.lower(text), F.lit(" \t\n\v\f\r")), "[ \\t-\\r]+")

    def rolled(hashes: Column) -> Column:
        return F.transform(F.sequence(F.lit(1), F.greatest(F.size(hashes) - (words - 1), F.lit(1))), lambda i: F.xxhash64(F.slice(hashes, i, words)))

    # What a lambda uses again and again is bound to a lambda's variable; else it would be computed each time.
    once = F.element_at(F.transform(F.array(F.transform(parts, lambda w: F.xxhash64(w))), rolled), 1)
    return F.when(F.trim(text, F.lit(" \t\n\v\f\r")) != "", once).otherwise(F.array().cast("array<long>"))


def placed(log_a: Column) -> Column:
    """The logarithm of a value as a whole number, by which candidates are ordered."""
    return ((log_a + F.lit(64.0)) * F.lit(float(1 << 24))).cast("long")


def reach(whole: Column) -> Column:
    """The rank that a sample must be below, by its own bag's size alone: no candidate below it is left out by ``sample``."""
    return placed(F.ln(F.lit(REACH) / whole))


def sample(term: Column, weight: Column, whole: Column, number: Column) -> Column:
    """A term's candidate for a sample: a long that orders by the value and ends in 32 bits that name term and level.

    The least value of a bag of weight ``whole`` is over REACH / whole once in exp(REACH) samples. A value is at least
    -ln(u3 u4) u1 u2 / weight in the uniform numbers, and with r = sqrt(u3 u4) that logarithm is at least
    4 (1 - r) / (1 + r), so most candidates are known to lose (null) without one.
    """
    one, two = F.xxhash64(term, number), F.xxhash64(number, term)  # the second one is needed by few candidates

    def uniform(h: Column, shift: int) -> Column:
        return (F.shiftrightunsigned(h, shift).bitwiseAND(F.lit((1 << 16) - 1)) + F.lit(0.5)) * F.lit(1 / (1 << 16))

    u12, u34, shift = uniform(one, 0) * uniform(one, 16), uniform(one, 32) * uniform(one, 48), uniform(two, 32)
    gamma, log_c = -F.ln(u12), F.ln(-F.ln(u34))
    level = F.floor(F.ln(weight) / gamma + shift)
    log_a = log_c - gamma * (level - shift + F.lit(1.0))  # between -64 and 4: the uniform numbers are 2 ** -17 at least
    rank = placed(log_a)
    name = two.bitwiseXOR(F.shiftleft(level, 13)).bitwiseAND(F.lit((1 << 32) - 1))
    root = F.sqrt(u34)
    return F.when((F.lit(1.0) - root) * u12 * whole <= weight * (REACH / 4) * (F.lit(1.0) + root), F.shiftleft(rank, 32).bitwiseOR(name))


def fingerprints(texts: DataFrame, keys: list[str], text: str = "text", words: int = 5, repeats: int = 64, slots: int = 1, carried: tuple[str, ...] = (), second: str | None = None) -> DataFrame:
    """keys, carried (columns of longs) and the fingerprint of ``repeats * slots`` samples; rows of equal keys are one bag.

    With ``second``, a text that shares most of its shingles with the first, also its ``second_fingerprint``: what both
    bags have with one weight is drawn once for the two.
    """
    # Carried values go before the terms, so that a row of the bag is only keys, a place and a number.
    names = ("fingerprint", "second_fingerprint")[: 1 if second is None else 2]
    sides, first, count = range(len(names)), len(carried) + 2, repeats * slots
    bag = texts.select(*keys, *carried, *[shingles(F.col(c), words).alias(f"bag{i}_") for i, c in zip(sides, (text, second), strict=False)])
    sizes = [F.size(f"bag{i}_").cast("long").alias(f"size{i}_") for i in sides]
    bag = bag.withColumns({f"size{i}_": c for i, c in enumerate(sizes)})
    listed = F.concat(F.array(F.lit(0).cast("long"), *[F.col(c) for c in carried], F.lit(0).cast("long")), *[F.col(f"bag{i}_") for i in sides])
    whole = [f"size{i}_" for i in sides]
    terms = bag.select(*keys, *whole, F.posexplode(listed).alias("at_", "term_"))
    of_second = F.col("at_") >= F.col("size0_") + first
    number = lambda c: F.sum(F.when(c, F.lit(1)).otherwise(F.lit(0)))
    terms = terms.withColumns({"place_": F.least("at_", F.lit(first)), "second_": of_second}).drop("at_")
    bags = terms.groupBy(*keys, *whole, "place_", "term_").agg(number(~F.col("second_")).alias("n0_"), number(F.col("second_")).alias("n1_"))
    # Side 0 and 1: a weight in one of the bags; side 2: one weight in both.
    pair = F.when(F.col("n0_") == F.col("n1_"), F.array(F.struct(F.lit(2).alias("side_"), F.col("n0_").cast("double").alias("w_"))))
    lone = lambda i: F.struct(F.lit(i).alias("side_"), F.col(f"n{i}_").cast("double").alias("w_"))
    apart = F.when(F.col("n1_") == 0, F.array(lone(0))).when(F.col("n0_") == 0, F.array(lone(1))).otherwise(F.array(lone(0), lone(1)))
    bags = bags.select(*keys, *whole, "place_", "term_", F.inline(F.coalesce(pair, apart)))
    # Other rows than terms have no weight and lose. A row takes part in groups of samples: the code of all at once is too long to be compiled.
    weight = F.when(F.col("place_") == first, F.col("w_")).otherwise(F.lit(0.0))
    groups = -(-count // GROUP)
    least = F.greatest(F.least(*whole) if second is not None else F.col("size0_"), F.lit(1)).cast("double")  # of what both bags have, none is left out for the other's size
    drawn = bags.select(*keys, *whole, "place_", "term_", "side_", weight.alias("w_"), F.coalesce("term_", F.lit(0).cast("long")).alias("hash_"), least.alias("whole_"), F.explode(F.sequence(F.lit(0), F.lit(groups - 1))).alias("g_"))
    drawn = drawn.groupBy(*keys, *whole, "side_", "g_").agg(
        *[F.max(F.when(F.col("place_") == i + 1, F.col("term_"))).alias(c) for i, c in enumerate(carried)],
        *[F.min(sample(F.col("hash_"), F.col("w_"), F.col("whole_"), F.col("g_") * GROUP + j)).alias(f"v{j}") for j in range(GROUP)],
    )
    parts = drawn.groupBy(*keys, "g_").agg(
        *[F.max(c).alias(c) for c in (*carried, *whole)],
        *[F.min(F.when(F.col("side_") != 1 - i, F.col(f"v{j}"))).alias(f"v{i}_{j}") for i in sides for j in range(GROUP)],
    )

    def digits(i: int, j: int) -> Column:
        v, size = F.col(f"v{i}_{j}"), F.greatest(f"size{i}_", F.lit(1)).cast("double")
        low = F.when(F.shiftright(v, 32) < reach(size), v.bitwiseAND(F.lit((1 << 32) - 1)) % 65535 + 1)
        return F.lpad(F.lower(F.hex(F.coalesce(low, F.lit(0)))), 4, "0")

    part = parts.select(*keys, *carried, "g_", *[F.concat(*[digits(i, j) for j in range(GROUP)]).alias(f"d{i}_") for i in sides])
    made = part.groupBy(*keys).agg(*[F.max(c).alias(c) for c in carried], *[F.max(F.when(F.col("g_") == g, F.col(f"d{i}_"))).alias(f"g{i}_{g}") for i in sides for g in range(groups)])
    return made.select(*keys, *carried, *[F.substring(F.concat(*[F.col(f"g{i}_{g}") for g in range(groups)]), 1, 4 * count).alias(n) for i, n in enumerate(names)])


def likeness(a: Column, b: Column, size: int = 64) -> Column:
    """Share of equal places among those that are not empty in both; 1.0 if all are."""
    at_ = F.sequence(F.lit(1), F.lit(4 * size), F.lit(4))
    used = F.size(F.filter(at_, lambda i: (F.substring(a, i, 4) != "0000") | (F.substring(b, i, 4) != "0000")))
    both = F.size(F.filter(at_, lambda i: F.substring(a, i, 4) == F.substring(b, i, 4)))  # those that are empty in both among them
    unlike = F.when(a.contains("0000") & b.contains("0000"), (both - F.lit(size) + used) / F.greatest(used, F.lit(1))).otherwise(both / F.lit(size))
    return F.when(a == b, F.lit(1.0)).otherwise(unlike)


def successors(keys: DataFrame, column: str) -> DataFrame:
    """(column, next) for a column of distinct whole numbers; next is null for the last. No task sees all keys."""
    grouped = keys.select(F.col(column).alias("k")).withColumn("g", F.expr(f"k div {SPAN}"))
    firsts = grouped.groupBy("g").agg(F.min("k").alias("first"))
    if firsts.count() <= SPAN:
        later = firsts.select("g", F.lead("first").over(Window.orderBy("g")).alias("after"))  # at most SPAN rows
    else:
        chain = successors(firsts, "g")
        later = chain.join(firsts.withColumnsRenamed({"g": "next", "first": "after"}), "next", "left").select("g", "after")
    within = grouped.withColumn("n", F.lead("k").over(Window.partitionBy("g").orderBy("k")))
    return within.join(later, "g").select(F.col("k").alias(column), F.coalesce("n", "after").alias("next"))


def edited(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """block, place, doc_id, text, edited: the last quarter gives way to the beginning of the next document."""
    order = F.coalesce(F.col("doc_id"), F.lit(-(1 << 62)))
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    rows = rows.withColumns({"o": order, "h": F.xxhash64("text")}).withColumn("block", F.expr(f"o div {BLOCK}"))
    chars = rows.agg(F.sum(F.octet_length("text")).alias("n")).first()["n"] or 0
    parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), chars // CHARS)
    # The first text of every block goes also to the block before.
    heads = rows.groupBy("block").agg(F.min_by("text", F.struct("o", "h")).alias("head"))
    blocks = written(rows.groupBy("block").agg(F.count("*").alias("n")).select("block"), "fingerprint-blocks")
    follows = successors(blocks, "block")
    first = blocks.agg(F.min("block").alias("b0"))
    follows = follows.crossJoin(F.broadcast(first)).select("block", F.coalesce("next", "b0").alias("next"))  # one row
    given = follows.join(heads.withColumnRenamed("block", "next"), "next").select("block", "head", "next")
    w = Window.partitionBy("block").orderBy("o", "h")
    dealt = rows.repartition(parts, "block").withColumns({"place": F.row_number().over(w), "after": F.lead("text").over(w)})
    joined = dealt.join(given.hint("shuffle_hash"), "block").withColumn("after", F.coalesce("after", "head"))
    n = F.char_length("text")
    cut = F.floor(n / 4).cast("int")
    changed = F.concat(F.substring("text", F.lit(1), n - cut), F.substring("after", F.lit(1), cut))
    return joined.select("block", "place", "next", "doc_id", "text", n.cast("long").alias("n_chars"), changed.alias("edited"))


def near(docs: DataFrame, key: str = "doc_id", text: str = "text", words: int = 5, repeats: int = 64) -> DataFrame:
    """Fingerprints of every text and its edited form, and how like they and the next document's are."""
    base = edited(docs, key, text)
    sha = F.sha2(F.encode("edited", "UTF-8"), 256)
    parts = [F.conv(F.substring("sha", 16 * i + 1, 16), 16, -10).cast("long").alias(f"sha{i}") for i in range(4)]  # signed
    one = base.withColumn("sha", sha).select("block", "place", "next", "doc_id", "n_chars", *parts, "text", "edited")
    carried = ("next", "doc_id", "n_chars", "sha0", "sha1", "sha2", "sha3")
    both = fingerprints(one, ["block", "place"], "text", words, repeats, carried=carried, second="edited").withColumnRenamed("second_fingerprint", "edited_fingerprint")
    digest = F.concat(*[F.lpad(F.lower(F.hex(f"sha{i}")), 16, "0") for i in range(4)])
    stored = written(both.withColumn("edited_sha256", digest).drop(*[f"sha{i}" for i in range(4)]), "fingerprints")
    heads = stored.where("place = 1").select(F.col("block").alias("next"), F.col("fingerprint").alias("head"))
    w = Window.partitionBy("block").orderBy("place")
    out = stored.withColumn("after", F.lead("fingerprint").over(w)).join(heads, "next").withColumn("after", F.coalesce("after", "head"))
    return out.select(
        "doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint",
        likeness(F.col("fingerprint"), F.col("edited_fingerprint"), repeats).alias("near_edited"),
        likeness(F.col("fingerprint"), F.col("after"), repeats).alias("near_next"),
    )
