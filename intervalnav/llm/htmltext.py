"""Main text of HTML pages: structure first, and a suffix array over each host's remaining token streams.

A page is read into blocks of text. Blocks in elements or classes that name page furniture are chrome; blocks
in an article (or main) container are the text; where a page has no such container its other blocks are open.
The streams of a host's pages are concatenated, and their suffix array gives the runs of ``run`` tokens (or whole
shorter blocks) that distinct pages share. Suffix arrays are made for the pages that a task holds anyway; counts of
distinct pages are summed over all tasks by (host, run), which is exact, since a page is in one task only.

Open blocks: chrome and open blocks are one stream; runs on at least ``pages`` pages are boilerplate.
Article blocks: runs in the articles of at least ``pages`` pages that are over half of the host's pages with an article
are boilerplate; fewer pages than that share passages of prose. Such a run has the majority of the host's articles in
one of the slices that pages are read in, so the slices' arrays name all candidates, and only these are counted.
A block that is mostly covered by boilerplate goes, unless nothing would be left of the page.

Defined cases: null html is empty and gives an empty text; broken markup is read as far as it makes sense
(unclosed elements end with their parents, an unclosed comment takes the rest); a null url is a host of its own;
pages of one host repeated under one id count as many; a host with one page has no boilerplate but chrome.
"""

from __future__ import annotations

import functools
import html
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import arrowtext as at
from .common import BITMAP, marked, written

RUN = 8
PAGES = 3
COVERED = 0.8
SLICE = 1 << 23  # bytes of pages whose articles share a suffix array
KEEP, CHROME, OPEN = 0, 1, 2

# Element names, roles and class words of page furniture, and the kinds of elements.
DROPPED = frozenset("nav header footer aside form script style noscript template iframe svg canvas object select button textarea head title dialog menu audio video map math".split())
ROLES = frozenset("navigation banner contentinfo complementary search form alert alertdialog dialog menu menubar toolbar".split())
FURNITURE = frozenset(
    "ad ads advert adverts advertisement advertising adsense banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notices notification alert popup modal overlay newsletter subscribe "
    "subscription signup social share sharing breadcrumb breadcrumbs menu nav navbar navigation sidebar header footer masthead comment comments commentlist disqus reply replies respond discussion related "
    "recommended recommendations pagination pager widget login search toolbar skip copyright disclaimer tags".split()
)
RAW = frozenset("script style textarea title noscript template iframe".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
CLOSES = {"p": {"p"}, "li": {"li", "p"}, "dt": {"dt", "dd", "p"}, "dd": {"dt", "dd", "p"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPES = frozenset("article main body html div section table ul ol dl td th blockquote nav header footer aside form".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^>]*>", re.S)
_NAMED = re.compile(r"(?i)\b(class|id|role|itemprop|hidden|aria-hidden|style)\b(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s\"'>]+))?")
_WORD = re.compile(r"[A-Za-z][a-z]*|[0-9]+")


def _reading(tag: str, attributes: str) -> tuple[bool, bool]:
    """Whether an element is furniture, and whether it holds the article."""
    drop, main = tag in DROPPED, tag in ("article", "main")
    if attributes and tag not in ("html", "body"):
        for name, value in _NAMED.findall(attributes):
            name, value = name.lower(), value.strip("\"'").lower() if name.lower() != "class" and name.lower() != "id" else value.strip("\"'")
            if name == "role":
                drop |= value in ROLES
                main |= value == "main"
            elif name == "itemprop":
                main |= value == "articlebody"
            elif name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and "display:none" in value.replace(" ", ""):
                drop = True
            elif name in ("class", "id"):
                drop |= any(w.lower() in FURNITURE for w in _WORD.findall(value))
    return drop, main and not drop


def blocks_of(page: str) -> list[tuple[int, str]]:
    """(kind, text) of the blocks in page order."""
    out: list[tuple[bool, bool, str]] = []
    stack: list[tuple[str, bool, bool, bool]] = []  # element; whether furniture, in the article, in inline furniture
    parts: list[str] = []
    state = outside = (False, False, False)
    any_main = False
    pos, n = 0, len(page)

    def flush() -> None:
        text = " ".join("".join(parts).split())
        parts.clear()
        if text:
            out.append((state[0], state[1], text))

    def cut(at_: int) -> None:
        nonlocal state
        del stack[at_:]
        state = stack[-1][1:] if stack else outside

    while pos < n:
        m = _TOKEN.search(page, pos)
        text = page[pos : m.start() if m else n]
        if text and not state[2]:
            parts.append(html.unescape(text))
        if not m:
            break
        pos = m.end()
        tag = m[2]
        if not tag:
            continue
        tag = tag.lower()
        block = tag not in INLINE
        if m[1]:
            open_ = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag), -1)
            if block or open_ >= 0 and any(e[0] not in INLINE for e in stack[open_:]):
                flush()
            if open_ >= 0:
                cut(open_)
            continue
        if tag == "br":
            parts.append(" ")
            continue
        if block:
            flush()
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] in CLOSES.get(tag, ()):
                    cut(i)
                    break
                if stack[i][0] in SCOPES:
                    break
        if tag in VOID:
            continue
        if tag in RAW:
            end = re.compile(rf"(?i)</{tag}\b[^>]*>").search(page, pos)
            pos = end.end() if end else n
            continue
        down, holds = _reading(tag, m[3])
        drop, main, skip = state
        stack.append((tag, drop or down, main or holds, skip) if block else (tag, drop, main, skip or down))
        state = stack[-1][1:]
        any_main |= state[1] and not state[0]
    flush()
    return [(CHROME if d else KEEP if a else CHROME if any_main else OPEN, t) for d, a, t in out]


def suffix_array(codes: np.ndarray, depth: int | None = None) -> np.ndarray:
    """Suffixes in order, by doubling; by their first ``depth`` members at least, where that is given."""
    n = len(codes)
    rank = np.unique(codes, return_inverse=True)[1].astype(np.int64)
    width = 1
    while True:
        after = np.full(n, -1, np.int64)
        after[: n - width] = rank[width:] if width < n else []
        order = np.lexsort((after, rank))
        new = np.zeros(n, np.int64)
        new[order[1:]] = np.cumsum((rank[order[1:]] != rank[order[:-1]]) | (after[order[1:]] != after[order[:-1]]))
        rank = new
        width *= 2
        if depth and width >= depth:
            return order
        if n < 2 or rank[order[-1]] == n - 1 or width >= n:
            return order


def common_prefixes(codes: np.ndarray, order: np.ndarray, limit: int) -> np.ndarray:
    """Length, up to ``limit``, of what each suffix shares with the one before it in the order."""
    n = len(codes)
    out = np.zeros(n, np.int64)
    alive = np.arange(1, n)
    for k in range(limit):
        a, b = order[alive - 1] + k, order[alive] + k
        fits = (a < n) & (b < n)
        alive, a, b = alive[fits], a[fits], b[fits]
        alive = alive[codes[a] == codes[b]]
        out[alive] = k + 1
    return out


@functools.lru_cache(1 << 17)
def _token(token: str) -> int:
    return xxhash.xxh64_intdigest(token)


def run_hashes(texts: list[str], run: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hash, block, place and the block's tokens of the runs that begin at each token; the last ones, and short blocks, end with the block."""
    tokens = [t.split() for t in texts]
    size = np.array([len(t) for t in tokens], np.int64)
    h = np.array([_token(t) for block in tokens for t in block], np.uint64)
    block = np.repeat(np.arange(len(texts)), size)
    place = np.arange(len(h)) - np.repeat(np.cumsum(size) - size, size)
    begins = np.flatnonzero(place <= np.maximum(size - run, 0)[block])
    key = np.zeros(len(begins), np.uint64)
    left = np.minimum(size[block[begins]], run)
    for j in range(min(run, int(size.max(initial=0)))):
        has = slice(None) if j == 0 or left.min() > j else left > j
        key[has] = key[has] * np.uint64(0x9E3779B97F4A7C15) + h[begins[has] + j]
    return at.mix(key + left.astype(np.uint64)).view(np.int64), block[begins], place[begins], size[block[begins]]


def windows(text: str, run: int) -> list[int]:
    """Hashes of the runs of tokens that begin at each token."""
    return run_hashes([text], run)[0].tolist()


def shared_runs(pages: list[list[str]], run: int) -> list[tuple[int, int]]:
    """(run hash, distinct pages) of every run in the pages' blocks, through one suffix array of all of them."""
    number: dict[str, int] = {}
    codes: list[int] = []
    owner: list[int] = []
    spans: list[tuple[int, int]] = []  # of every block
    stop = -1
    for i, blocks in enumerate(pages):
        for text in blocks:
            tokens = text.split()
            spans.append((len(codes), len(tokens)))
            codes += [number.setdefault(t, len(number)) for t in tokens]
            codes.append(stop)  # no two ends are equal, so no run goes past a block
            owner += [i] * (len(tokens) + 1)
            stop -= 1
    if not codes:
        return []
    c, own = np.array(codes), np.array(owner)
    size = np.zeros(len(c), np.int64)  # of the run that begins here; 0: none
    for a, n in spans:
        if n:
            size[a : a + max(1, n - run + 1)] = min(n, run)
    order = suffix_array(c, run)
    lcp = common_prefixes(c, order, run)
    key = np.zeros(len(c), np.int64)
    key[size > 0] = run_hashes([text for blocks in pages for text in blocks], run)[0]
    out: list[tuple[int, int]] = []
    # Neighbours in the order that share their whole run are one group; short blocks must also end alike.
    for width in np.unique(size[size > 0]).tolist():
        ends_here = size[order] == width
        spots = np.flatnonzero(ends_here)
        between = np.minimum.reduceat(np.append(lcp, 0), spots + 1)[: len(spots) - 1] if len(spots) > 1 else np.zeros(0, np.int64)
        group = np.concatenate([[0], np.cumsum(between < width)])
        pages_of = np.unique(group * len(pages) + own[order[spots]]) // len(pages)
        first = order[spots[np.flatnonzero(np.r_[True, between < width])]]
        out += zip(key[first].tolist(), np.bincount(pages_of).tolist(), strict=True)
    return out


def _host(url: str | None) -> str:
    m = re.search(r"://([^/?#]*)", url or "")
    return m[1].lower() if m else ""


def _number(host: str) -> int:
    return xxhash.xxh64_intdigest(host) - (1 << 63)


def extract(pages: DataFrame, key: str = "page_id", url: str = "url", source: str = "html", run: int = RUN, least: int = PAGES) -> DataFrame:
    """page_id, url, text and n_chars of every page."""
    raw = pages.select(F.col(key).alias("page_id"), F.col(url).alias("url"), F.col(source).alias("html"))
    id_type = raw.schema["page_id"].dataType.simpleString()

    def majority(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "html", SLICE):
                hosts: dict[str, list[list[str]]] = {}
                for url_, page in zip(part.column("url").to_pylist(), part.column("html").to_pylist(), strict=True):
                    if own := [t for k, t in blocks_of(page or "") if k == KEEP]:
                        hosts.setdefault(_host(url_), []).append(own)
                rows = [(_number(host), r) for host, own in hosts.items() for r, k in shared_runs(own, run) if 2 * k > len(own)]
                yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in rows], pa.int64()) for i in range(2)], names=["host", "r"])

    # Candidates in a filter of bounded size; others that pass it are counted for nothing.
    named = raw.mapInArrow(at.lean(majority), "host long, r long").distinct().withColumn("key", F.col("host").bitwiseXOR(F.col("r")))
    place, bit = F.pmod("key", F.lit(BITMAP)).cast("int"), F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned("key", 40).bitwiseAND(F.lit(63)).cast("int"))
    words = named.groupBy(place.alias("word")).agg(F.bit_or(bit).alias("bits")).toArrow()
    bits = np.zeros(BITMAP, np.int64)
    bits[words.column("word").to_numpy()] = words.column("bits").to_numpy()
    candidates = pages.sparkSession.sparkContext.broadcast(bits.view(np.uint64))

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "html"):
                texts, left, of, has_article = [], [], [], []
                for url_, page in zip(part.column("url").to_pylist(), part.column("html").to_pylist(), strict=True):
                    found = blocks_of(page or "")
                    is_open = any(k == OPEN for k, _ in found)
                    own = [t for k, t in found if k == (OPEN if is_open else KEEP)]
                    host = _number(_host(url_))
                    r, block, spot, size = run_hashes(own, run)
                    if not is_open:
                        key = r ^ host
                        hit = (candidates.value[key % BITMAP] >> (key.view(np.uint64) >> np.uint64(40) & np.uint64(63)) & np.uint64(1)) > 0
                        r, block, spot = r[hit], block[hit], spot[hit]
                    unsure = is_open or len(r) > 0
                    texts.append(None if unsure else "\n".join(own))
                    of.append(host)
                    has_article.append(bool(own) and not is_open)
                    cuts = np.searchsorted(block, np.arange(len(own) + 1)).tolist()
                    runs = list(zip(spot.tolist(), r.tolist(), strict=True))
                    left.append([{"text": t, "runs": [{"i": i, "r": x} for i, x in runs[a:b]], "size": len(t.split())} for t, a, b in zip(own, cuts, cuts[1:], strict=False)] if unsure else [])
                yield pa.RecordBatch.from_arrays([part.column("page_id"), part.column("url"), pa.array(of, pa.int64()), pa.array(has_article, pa.bool_()), pa.array(texts, pa.string()), pa.array(left, _LEFT)], names=["page_id", "url", "host", "article", "text", "left"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "html"):
                hosts: dict[str, list[list[str]]] = {}
                for url_, page in zip(part.column("url").to_pylist(), part.column("html").to_pylist(), strict=True):
                    hosts.setdefault(_host(url_), []).append([t for k, t in blocks_of(page or "") if k != KEEP])
                rows = [(_number(host), r, k) for host, own in hosts.items() for r, k in shared_runs(own, run)]
                yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in rows], pa.int64()) for i in range(3)], names=["host", "r", "n"])

    # Texts are written once; runs outside articles are counted only on hosts that have a page without a container.
    parsed = written(raw.mapInArrow(at.lean(parse), f"page_id {id_type}, url string, host long, article boolean, text string, left array<struct<text: string, runs: array<struct<i: int, r: long>>, size: int>>").withColumn("rid", F.monotonically_increasing_id()), "html-parsed")
    plain = parsed.where("text is not null").select("page_id", "url", "text")
    unsure = parsed.where("text is null").select("rid", "page_id", "url", "host", "article", "left")
    own_host = F.xxhash64(F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), "://([^/?#]*)", 1)))
    hosts = unsure.where("not article").select(own_host.alias("own_host")).distinct()
    # A filter of bounded size: hosts that pass it by chance are counted for nothing, and no page is shuffled.
    asked = marked(raw.withColumn("own_host", own_host), "own_host", hosts).where("__marked").select(*raw.columns)
    shared = asked.mapInArrow(count, "host long, r long, n long").groupBy("host", "r").agg(F.sum("n").alias("n")).where(F.col("n") >= least)
    blocks = unsure.select("rid", "host", "article", F.posexplode("left").alias("b", "x")).select("rid", "host", "article", "b", "x.size", F.explode("x.runs").alias("y")).select("rid", "host", "article", "b", "size", "y.i", "y.r")
    articles = blocks.where("article").groupBy("host", "r").agg(F.count_distinct("rid").alias("n")).where(F.col("n") >= least)
    articles = articles.join(parsed.where("article").groupBy("host").agg(F.count("*").alias("pages")), "host").where("2 * n > pages")
    boilerplate = shared.select("host", "r", F.lit(False).alias("article")).union(articles.select("host", "r", F.lit(True).alias("article")))
    hit = blocks.join(boilerplate, ["host", "r", "article"], "left_semi")
    # Tokens covered: the places of the runs that are shared, each as long as a run or the block.
    spread = hit.select("rid", "b", "size", F.explode(F.sequence(F.col("i"), F.least(F.col("i") + (run - 1), F.col("size") - 1))).alias("token")).groupBy("rid", "b", "size").agg(F.count_distinct("token").alias("covered"))
    gone = written(spread.where(F.col("covered") >= COVERED * F.col("size")).groupBy("rid").agg(F.collect_set("b").alias("gone")), "html-gone")
    # Pages that lose no block are not shuffled, but for those that pass the filter by chance.
    unsure = marked(unsure.select("rid", "page_id", "url", "left"), "rid", gone.select("rid"))
    joined = unsure.where("__marked").join(gone, "rid", "left").select("page_id", "url", "left", "gone")
    joined = joined.union(unsure.where("not __marked").select("page_id", "url", "left", F.lit(None).cast("array<int>")))
    kept = F.filter("left", lambda _, i: ~F.coalesce(F.array_contains("gone", i), F.lit(False)))
    chosen = F.when(F.size(kept) == 0, F.col("left")).otherwise(kept)
    rest = joined.select("page_id", "url", F.array_join(F.transform(chosen, lambda x: x["text"]), "\n").alias("text"))
    return plain.union(rest).withColumn("n_chars", F.char_length("text").cast("long"))


_LEFT = pa.list_(pa.struct([("text", pa.string()), ("runs", pa.list_(pa.struct([("i", pa.int32()), ("r", pa.int64())]))), ("size", pa.int32())]))
