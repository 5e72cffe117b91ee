"""The corpus operators against brute force on small tables with nulls, empty and long texts, ties and repeats."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from intervalnav.llm import arrowtext, bytebpe, fingerprint, flac, gatedlm, htmltext, jaccard, langid, linededup, packing, urlfilter
from intervalnav.llm.components import connected

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score string, h string"
WORD = re.compile("[^\x20\x09-\x0d]+")


def low(text):
    return (text or "").translate({c: c + 32 for c in range(65, 91)})


def corpus(n=40, seed=1):
    rng = random.Random(seed)
    words = {"xx": "kal bor tin mesa dru fol".split(), "yy": "qui zew vax ypo jig hux".split()}
    out = []
    for i in range(n):
        lang = rng.choice(["xx", "yy"])
        lines = [" ".join(rng.choice(words[lang]) + rng.choice(["", "a", "os"]) for _ in range(rng.randint(3, 25))) for _ in range(rng.randint(1, 5))]
        out.append((i, "\n".join(lines), lang))
    for i in range(n, n + 12):  # near and exact copies
        d, text, lang = rng.choice(out)
        w = text.split(" ")
        if i % 3:
            w[rng.randrange(len(w))] = "Zed"
        out.append((i, " ".join(w), lang))
    odd = [None, "", "  \n\t ", "one", "Two words", "123 456 !!", "é" * 30, "İstanbul ﬁ ſ 日本 🙂\u0301", "a" * 70_000 + " " + "long words here " * 3000]
    out += [(1000 + i, t, None if i % 2 else "xx") for i, t in enumerate(odd)]
    return [(i, t, lang, "s", len(t or ""), "clash", "clash") for i, t, lang in out]


ROWS = corpus()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(5)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


# ---- shared -------------------------------------------------------------------------------------------------

def test_words_and_blocks():
    texts = ["ab  c", None, "", " x", "é\ny ", "q"]
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], names=["t"])
    for part in [*arrowtext.blocks(batch, "t", 3), batch]:
        data, offs = arrowtext.string_buffers(part.column("t"))
        s, e, r = arrowtext.words(data, offs)
        got = [(int(i), bytes(data[a:b]).decode()) for a, b, i in zip(s, e, r, strict=True)]
        assert got == [(i, w) for i, t in enumerate(part.column("t").to_pylist()) for w in WORD.findall(t or "")]
    data, offs = arrowtext.string_buffers(pa.array(["ab ba ab", "ab"]))
    h = arrowtext.span_hashes(data, *arrowtext.words(data, offs)[:2])
    assert h[0] == h[2] == h[3] != h[1]
    assert sum(p.num_rows for p in arrowtext.blocks(batch, "t", 1)) == len(texts)


def test_components(spark):
    rng = random.Random(4)
    pairs = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(500 + i, 501 + i) for i in range(60)] + [(700, 700 + i) for i in range(50)]
    parent = {x: x for p in pairs for x in p}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    got = dict(connected(spark.createDataFrame(pairs, "u long, v long")).collect())
    assert got == {x: find(x) for x in parent if find(x) != x}
    assert connected(spark.createDataFrame([], "u long, v long")).count() == 0
    for held in (40, 1000):  # several tasks, or one
        assert dict(connected(spark.createDataFrame(pairs, "u long, v long"), held=held).collect()) == got
    assert connected(spark.createDataFrame([], "u long, v long"), held=40).count() == 0


def test_few_jobs_join_few_sets(spark, docs):
    """Over a hundred jobs fell to rounds over a handful of edges; their plans filled the driver's memory."""
    context = spark.sparkContext
    context.setJobGroup("few-sets", "components")
    try:
        jaccard.components(docs).collect()
        assert len(context.statusTracker().getJobIdsForGroup("few-sets")) < 100
    finally:
        context.setLocalProperty("spark.jobGroup.id", None)


# ---- 1 ------------------------------------------------------------------------------------------------------

def test_langid(docs, empty):
    model = langid.learn(docs.where("doc_id % 4 != 2"))
    assert model.languages == ["xx", "yy"]
    got = by_id(langid.identify(docs, model))
    for i, text, lang, *_ in ROWS:
        if not any(c.isalpha() for c in text or ""):
            assert got[i]["lang_pred"] == "und" and got[i]["score"] == 0
        elif i < 60:
            assert got[i]["lang_pred"] == lang and 0 < got[i]["score"] <= 1
    none = langid.learn(empty)
    assert {r["lang_pred"] for r in langid.identify(docs, none).collect()} == {"und"} and langid.identify(empty, model).count() == 0


def test_langid_answers_for_each_gram_like_sets(docs):
    """What the filters say of an n-gram covers the exact sets, and exceeds them seldom."""
    p = langid.Params(per_language=10_000)
    model = langid.learn(docs, params=p)
    codes, _ = langid.grams(pa.array([t for _, t, *_ in ROWS]), p.orders)
    held = np.full(len(codes), ~np.uint64(0))
    for slot in langid.slots_of(codes, p.probes, p.slots):
        held &= model.masks[slot]
    count, total = Counter(), Counter()
    for _, t, lang, *_ in ROWS:
        if t is not None and lang:
            own = langid.grams(pa.array([t]), p.orders)[0].tolist()
            count.update((lang, g) for g in own)
            total[lang] += len(own)
    for i, lang in enumerate(model.languages):
        rate = lambda x, g: count[x, g] / total[x]
        want = np.array([count[lang, g] >= p.least_count and rate(lang, g) >= p.least_share * max(rate(x, g) for x in model.languages) for g in codes.tolist()])
        has = (held >> np.uint64(i)) & np.uint64(1) != 0
        assert (has | ~want).all() and (has & ~want).mean() < 0.01


# ---- 2 ------------------------------------------------------------------------------------------------------

@pytest.fixture(scope="module")
def bpe():
    return bytebpe.Coder(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


@pytest.fixture(scope="module")
def oracle():
    import tiktoken

    ranks = bytebpe.load_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_equals_the_library(bpe, oracle):
    rng = random.Random(2)
    texts = [t or "" for _, t, *_ in ROWS] + ["".join(rng.choice("abe  ß日🙂\n\t'sl.12²_<|endoftext|>") for _ in range(rng.randint(0, 50))) for _ in range(400)] + [" " * 500, "the" * 200, "=" * 900]
    for t in texts:
        joined = bpe.encode(t)
        assert joined == " ".join(map(str, oracle.encode_ordinary(t)))
        assert bpe.decode_all(joined) == t == "".join(bpe.decode(joined.split()))


def test_utf8_machine_streams_like_the_decoder():
    rng = random.Random(3)
    for _ in range(300):
        data = bytes(rng.choice([65, 0xC3, 0xA9, 0xE2, 0x82, 0xAC, 0xF0, 0x9F, 0x99, 0x82, 0xED, 0xA0, 0xC0, 0xFF, 0xF4, 0x90]) for _ in range(rng.randint(0, 14)))
        m = bytebpe.Utf8Machine()
        assert "".join(m.feed(data[i : i + 1]) for i in range(len(data))) + m.finish() == data.decode("utf-8", "replace")


def test_bpe_query(docs, empty, oracle):
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    got = by_id(bytebpe.code(docs, path, public_tokenizers.PATTERN, with_ids=True))
    for i, t, *_ in ROWS:
        ids = oracle.encode_ordinary(t or "")
        assert got[i]["ids"] == ids and got[i]["decoded"] == (t or "") and got[i]["n_tokens"] == len(ids)
        assert got[i]["decoded_sha256"] == hashlib.sha256((t or "").encode()).hexdigest()
    assert bytebpe.code(empty, path, public_tokenizers.PATTERN).count() == 0


# ---- 3 ------------------------------------------------------------------------------------------------------

def test_suffix_array():
    rng = random.Random(1)
    for _ in range(100):
        c = np.array([rng.randrange(3) for _ in range(rng.randint(1, 40))])
        order = htmltext.suffix_array(c)
        assert order.tolist() == sorted(range(len(c)), key=lambda i: c[i:].tolist())
    for pages in ([["a b c d e", "x y"], ["b c d e f", "x y", "x"], ["a b c d", "x y z"]], [[]], [["q"]]):
        want = Counter()
        for p in pages:
            want.update({w for t in p for w in htmltext.windows(t, 3)})
        assert Counter(dict(htmltext.shared_runs(pages, 3))) == want


def test_html_structure():
    page = '<article><header>h</header><h1>T&eacute;</h1><p><b>x<br>y<p>para <span class="ad">buy</span> more<section class="comments"><article><p>c</article></section></article>out<script>"</p>"</script><!-- <p>z'
    assert [t for k, t in htmltext.blocks_of(page) if k == htmltext.KEEP] == ["Té", "x y", "para more"]
    assert htmltext.blocks_of("") == [] and htmltext.blocks_of("a < b &amp; c") == [(htmltext.OPEN, "a < b & c")]


def test_html_boilerplate_in_articles(spark):
    share = "Share this story with your friends and tell us what you think"
    page = lambda i, body: f"<body><article><h1>Title {i}</h1><div>{share}</div><p>{body}</p></article></body>"
    prose = [f"own words number {i} of page {i * 7} and {i * 31} and yet more of them" for i in range(20)]
    copied = "a passage of prose that four of the articles have in common with each other"
    rows = [(i, f"http://h{i % 2}.org/{i}", page(i, copied if i < 8 else prose[i])) for i in range(20)]  # on four of ten pages of a host
    rows += [(50, "http://few.org/1", page(50, "one")), (51, "http://few.org/2", page(51, "two")), *((60 + i, "http://same.org/", f"<main>{share}</main>") for i in range(3))]
    got = {r["page_id"]: r["text"] for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string").repartition(6)).collect()}
    for i in range(20):
        assert got[i] == f"Title {i}\n{copied if i < 8 else prose[i]}"
    assert got[50] == f"Title 50\n{share}\none" and got[60] == got[61] == got[62] == share


def test_html_query(spark):
    menu = "Home News About Contact Terms Privacy Help Search Login"
    page = lambda i: f"<body><div>{menu}</div><div><p>own words number {i} of page {i * 7} and {i * 31} more</p></div></body>"
    rows = [(i, f"http://h{i % 2}.org/{i}", page(i)) for i in range(12)]
    rows += [(50, None, None), (51, "x", ""), (52, "http://lone.org/", page(52)), (53, "http://h0.org/z", f"<div>{menu}</div>"), (54, "http://h1.org/a", "<article><p>" + "long word " * 20_000 + "</article>")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit("clash")).repartition(4)
    got = {r["page_id"]: r for r in htmltext.extract(pages).collect()}
    for i in range(12):
        assert got[i]["text"] == f"own words number {i} of page {i * 7} and {i * 31} more"
    assert got[50]["text"] == got[51]["text"] == "" and got[52]["text"].startswith("Home") and got[53]["text"] == menu
    assert got[54]["n_chars"] == 20_000 * 10 - 1
    assert htmltext.extract(pages.limit(0)).count() == 0


# ---- 4 ------------------------------------------------------------------------------------------------------

def brute_components(rows, n=3, percent=90):
    sets = {}
    for i, t, *_ in rows:
        w = WORD.findall(low(t))
        sets[i] = {tuple(w[j : j + n]) for j in range(max(1, len(w) - n + 1))} if w else set()
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in sets}


def edited_rows(seed=7):
    rng, rows = random.Random(seed), []
    for g in range(12):
        base = [f"w{rng.randrange(400)}" for _ in range(rng.choice([4, 9, 30, 80, 300]))]
        for _ in range(rng.randint(1, 9)):
            w = list(base)
            for _ in range(rng.choice([0, 0, 1, 1, 2, 4])):
                w[rng.randrange(len(w))] = f"v{rng.randrange(9)}"
            rows.append((len(rows), " ".join(w)))
    return rows


@pytest.mark.parametrize("small_blocks", [False, True])
def test_jaccard(spark, docs, empty, small_blocks, monkeypatch):
    if small_blocks:
        monkeypatch.setattr(jaccard, "MINOR", 2)
        monkeypatch.setattr(jaccard, "MAJOR", 3)
    rows = [(i, t) for i, t, *_ in ROWS] + [(5000 + i, t) for i, t in edited_rows()]
    got = by_id(jaccard.components(spark.createDataFrame(rows, "doc_id long, text string").repartition(6)))
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == brute_components(rows)
    if not small_blocks:
        assert jaccard.components(empty).count() == 0
        twice = docs.union(docs)
        assert jaccard.components(twice).count() == 2 * len(ROWS)


@pytest.mark.parametrize("sampled", [2_000_000, 300])
def test_jaccard_below_the_segments_percentage(spark, sampled, monkeypatch):
    monkeypatch.setattr(jaccard, "SAMPLED", sampled)
    rng, rows = random.Random(3), [(i, t) for i, t, *_ in ROWS] + [(5000 + i, t) for i, t in edited_rows(8)]
    base = [f"w{i}" for i in range(2000)]
    rows += [(9000 + k, " ".join(w if rng.random() > rate else f"v{rng.randrange(10**6)}" for w in base)) for k, rate in enumerate([0, 0.01, 0.015, 0.02, 0.03])]
    got = by_id(jaccard.components(spark.createDataFrame(rows, "doc_id long, text string").repartition(6), n=5, percent=80))
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == brute_components(rows, 5, 80)


def test_trie_finds_all_links():
    rng = random.Random(5)
    sets = []
    for _ in range(15):
        base = sorted(rng.sample(range(3000), rng.choice([1, 5, 64, 65, 200])))
        for _ in range(4):
            s = set(base) ^ set(rng.sample(range(3000), rng.choice([0, 1, 6])))
            sets.append(np.array(sorted(s or {1}), np.uint64))
    trie = jaccard.Trie(sets)
    for i, x in enumerate(sets):
        want = [j for j, y in enumerate(sets) if 100 * len(set(x.tolist()) & set(y.tolist())) >= 90 * len(set(x.tolist()) | set(y.tolist()))]
        assert sorted(trie.links(x, 90).tolist()) == want and i in want


def test_sketches_refute_only_what_cannot_link():
    rng, sets = random.Random(6), []
    for size in (1, 5, 60, 64, 65, 130, 300, 1500):
        base = [rng.getrandbits(64) for _ in range(size)]
        for changed in (0, 1, size // 12, size // 9, size // 5, size):
            sets.append(sorted({*base[changed:], *(rng.getrandbits(64) for _ in range(changed))}))
    code, offs = np.array([x for s in sets for x in s], np.uint64), np.cumsum([0, *map(len, sets)])
    bits, size = jaccard.sketches(code, offs), np.diff(offs)
    for percent in (80, 90):
        dropped = 0
        for i, a in enumerate(sets):
            for j, b in enumerate(sets[:i]):
                may = jaccard.unrefuted(size[[i, j]], np.array([0, 1]), np.array([0, 1]), [bits[i], bits[j]], percent)
                links = 100 * len(set(a) & set(b)) >= percent * len(set(a) | set(b))
                assert may.all() or not may.any() and not links
                dropped += not may.any()
        assert dropped > 0.8 * len(sets) * (len(sets) - 1) / 2
        assert not jaccard.unrefuted(size, np.zeros(len(sets), np.int64), None, bits, percent).any()  # one component


def test_texts_of_sets_that_cannot_link_stay_where_they_are(spark, monkeypatch):
    rng, kept, write = random.Random(9), {}, jaccard.written

    def counted(df, name):
        out = write(df, name)
        kept[name] = out.count()
        return out

    monkeypatch.setattr(jaccard, "written", counted)
    base = [f"w{i}" for i in range(400)]
    rows = [(k, " ".join(w if rng.random() > 0.08 else f"v{rng.randrange(10**6)}" for w in base)) for k in range(12)]
    got = by_id(jaccard.components(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), n=5, percent=80))
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == brute_components(rows, 5, 80)
    assert kept["sets-held"] and sum(n for name, n in kept.items() if name.endswith("-texts")) == 0


# ---- 5 ------------------------------------------------------------------------------------------------------

def lev(a, b):
    p = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        q = [i]
        for j, y in enumerate(b, 1):
            q.append(min(p[j] + 1, q[-1] + 1, p[j - 1] + (x != y)))
        p = q
    return p[-1]


def mangled(rng, s, k):
    s = list(s)
    for _ in range(k):
        i = rng.randrange(len(s))
        rng.choice([lambda: s.__setitem__(i, rng.choice("abé ")), lambda: s.insert(i, rng.choice("abé")), lambda: s.pop(i)])()
    return "".join(s)


@pytest.mark.parametrize("edits", [1, 2, 3])
def test_banded_distance(spark, edits):
    rng = random.Random(edits)
    base = ["".join(rng.choice("abcé ") for _ in range(rng.randint(12, 40))) for _ in range(60)]
    rows = [(a, mangled(rng, a, rng.randint(0, edits + 2))) for a in base]
    rows = [(a, b) for a, b in rows if abs(len(a) - len(b)) <= edits]
    for r in linededup.with_distance(spark.createDataFrame(rows, "a string, b string"), "a", "b", edits).collect():
        d = lev(r["a"], r["b"])
        assert r["distance"] == d if d <= edits else r["distance"] > edits


@pytest.mark.parametrize("edits", [1, 2])
def test_line_classes(spark, edits):
    rng, lines = random.Random(8), []
    for _ in range(40):
        a = "".join(rng.choice("abcdeé ") for _ in range(rng.randint(14, 40))).strip() + "x"
        lines.append(a)
        for _ in range(rng.randint(0, 4)):
            lines.append(mangled(rng, rng.choice(lines[-3:]), rng.randint(0, edits)))
    rng.shuffle(lines)
    rows = [(i, "\n".join(lines[5 * i : 5 * i + 5])) for i in range(len(lines) // 5 + 1)] + [(900, None), (901, ""), (902, "a\n\n \na\nab")]
    got = {(r[0], r[1]): (r["class_doc"], r["class_line"], r["kept"]) for r in linededup.classes(spark.createDataFrame(rows, "doc_id long, text string"), edits=edits, least=12).collect()}
    place = [(d, i, x.strip(" \t\r\f\v")) for d, t in rows for i, x in enumerate((t or "").split("\n")) if x.strip(" \t\r\f\v")]
    parent = list(range(len(place)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, (_, _, a) in enumerate(place):
        for j, (_, _, b) in enumerate(place[:i]):
            if a == b or min(len(a), len(b)) >= 12 and abs(len(a) - len(b)) <= edits and lev(a, b) <= edits:
                x, y = find(i), find(j)
                parent[max(x, y)] = min(x, y)
    assert got == {p[:2]: (*place[find(i)][:2], find(i) == i) for i, p in enumerate(place)}


def test_lines_are_cut(docs, empty):
    assert linededup.classes(empty).count() == 0
    cut = linededup.without_repeats(docs)
    assert cut.columns == docs.columns
    got, seen = by_id(cut), set()
    assert got[1000]["text"] is None and got[1001]["text"] == "" and len(got) == len(ROWS)
    for i, t, *_ in sorted(ROWS, key=lambda r: r[0]):
        for line in (t or "").split("\n"):
            key = line.strip(" \t\r\f\v")
            if key and key not in seen:
                seen.add(key)
                assert len(key) >= 60 or line in got[i]["text"].split("\n")


# ---- 6 ------------------------------------------------------------------------------------------------------

def test_language_model(spark, docs, empty):
    held = lambda i: zlib.crc32(str(i).encode()) % 7 == 2
    c = Counter()
    for i, t, *_ in ROWS:
        if not held(i):
            c.update([*WORD.findall(low(t)), "\n"])
    n, v = sum(c.values()), len(c)
    for p in (gatedlm.Params(head=4, vocabulary=4, hidden=4), gatedlm.Params(head=100, vocabulary=20, classes=4)):
        out = gatedlm.score(docs, F.crc32(F.col("doc_id").cast("string")) % 7 != 2, p=p)
        for i, r in by_id(out).items():
            words = [*WORD.findall(low(next(t for j, t, *_ in ROWS if j == i))), "\n"]
            assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(words), sum(c[w] > 0 for w in words), n)
            assert r["base_score"] == pytest.approx(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in words))
            assert r["score"] < 0
    assert gatedlm.score(empty, F.lit(True)).count() == 0
    untrained = gatedlm.score(docs, F.lit(False)).first()
    assert untrained["train_tokens"] == 0 and untrained["n_known"] == 0


def test_network_sums_to_one_and_its_slopes_are_right():
    p = gatedlm.Params(hidden=3, classes=3)
    net = gatedlm.Network(np.array([5, 4, 9, 2, 1]), p)
    h = np.random.default_rng(1).standard_normal((1, 3)).astype(np.float32)
    total = sum(math.exp(gatedlm._output(net, h, np.array([y]))[0][0]) for y in range(5))
    assert total == pytest.approx(1, abs=1e-5)
    grad = net.like()
    y = np.array([2])
    _, dh = gatedlm._output(net, h, y, grad)
    for j in range(3):
        step = np.zeros_like(h)
        step[0, j] = 1e-2
        slope = (gatedlm._output(net, h + step, y)[0] - gatedlm._output(net, h - step, y)[0]) / 2e-2
        assert -slope[0] == pytest.approx(float(dh[0, j]), abs=2e-3)


# ---- 7 ------------------------------------------------------------------------------------------------------

RULES = [("com", "/", False), ("example.com", "/en/", True), ("www.example.com", "/en/", False), ("net", "/es/", True), ("net", "/fr/", True)]
URLS = [None, "", "no scheme", "http://www.example.com/en/1", "https://EXAMPLE.com/en/", "http://a.example.com/en", "http://x.net/es/?q", "http://xnet/es/", "http://net/fr/#a", "http://com", "http://com/", "ftp://a.b.org/x://y.com/", "http://x.com?u=/en/"] * 2


@pytest.mark.parametrize("limit", [None, 0])
def test_url_rules(spark, limit, monkeypatch):
    if limit is not None:
        monkeypatch.setattr(urlfilter, "MAX_RULE_BYTES", limit)  # the way of large lists
    pages = spark.createDataFrame(list(enumerate(URLS)), "page_id long, url string").withColumn("rule", F.lit("clash"))
    for r in urlfilter.judge(pages, RULES).collect():
        m = re.match(r"(?s)^.*?://([^/?#]*)([^?#]*)", URLS[r["page_id"]] or "")
        host, path = (low(m[1]), m[2]) if m else ("", "")
        fits = [(len(h + p), h + p, b) for h, p, b in RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fits, default=(0, None, False))
        assert (r["host"], r["path"], r["rule"], r["verdict"]) == (host, path, best[1], "block" if best[2] else "allow")
    assert urlfilter.judge(pages.limit(0), RULES).count() == 0 and urlfilter.judge(pages, []).where("rule is not null").count() == 0


def test_digest_collisions_are_confirmed(monkeypatch):
    monkeypatch.setattr(urlfilter.xxhash, "xxh64_intdigest", lambda s: 7)
    table = urlfilter.DigestArray(np.frombuffer(urlfilter.DigestArray.pack({"a": 1, "b": 0, "cc": 1}), np.uint8))
    assert [table.string(p) if p >= 0 else None for p in table.find([b"cc", b"x", b"a"])] == [b"cc", None, b"a"]


# ---- 8 ------------------------------------------------------------------------------------------------------

def test_flac_round_trip():
    rng = random.Random(3)
    texts = ["", None, "a", "a" * 64, "ab" * 5000, "\x00" * 500, *(t for _, t, *_ in ROWS), *("".join(chr(rng.randint(0, 255)) for _ in range(rng.randint(0, 5000))) for _ in range(8))]
    payload, offs, size = flac.payloads(pa.array(texts, pa.string()))
    streams = flac.encode(payload, offs)
    samples, back, first = flac.decode(streams)
    assert (back == offs).all() and ((samples.view(np.uint8) ^ 0x80) == payload).all() and size[1] == 0
    for i in (0, 3, 4, 5, len(texts) - 1):  # sample by sample
        _, _, seek, pos = flac._metadata(streams[i])
        got: list[int] = []
        for q in seek:
            h = pos + int(q["offset"]) + 4 + 1 + 3
            got += flac.scalar_subframe(streams[i][h : h + 2 * int(q["count"]) + 60], int(q["count"]))
        assert got == samples[back[i] : back[i + 1]].tolist()
    for spot in (-1, -40):
        bad = bytearray(streams[4])
        bad[spot] ^= 4
        with pytest.raises(ValueError):
            flac.decode([bytes(bad)])


def test_flac_other_forms():
    """A subframe of order 3 in two partitions, the second with escape, written here bit by bit."""
    x = [3, -2, 5, 7, 1, 0, 2, 2]
    bits = "0" + "001011" + "0" + "".join(f"{v & 255:08b}" for v in x[:3]) + "00" + "0001"
    e = [x[i] - 3 * x[i - 1] + 3 * x[i - 2] - x[i - 3] for i in range(3, 8)]
    zig = [(v << 1) ^ (v >> 31) for v in e]
    bits += "0010" + "".join("0" * (z >> 2) + "1" + f"{z & 3:02b}" for z in zig[:1]) + "1111" + "00111" + "".join(f"{v & 127:07b}" for v in e[1:])
    bits += "0" * (-len(bits) % 8)
    assert flac.scalar_subframe(int(bits, 2).to_bytes(len(bits) // 8), 8) == x


def test_flac_query(docs, empty):
    out = by_id(flac.media(docs, with_media=True))
    for i, t, *_ in ROWS:
        raw = (t or "").encode()
        padded = raw + bytes(max(64, -(-len(raw) // 64) * 64) - len(raw))
        r = out[i]
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-64:]))
        assert r["media_bytes"] == len(r["media"]) and r["media_sha256"] == hashlib.sha256(r["media"]).hexdigest()
    blocks = flac.pcm_blocks(flac.media(docs, with_media=True)).groupBy("doc_id").agg(F.sum("n_samples").alias("n"), F.max("first_sample").alias("f")).collect()
    assert {r["doc_id"]: r["n"] for r in blocks} == {i: r["payload_bytes"] for i, r in out.items()}
    assert flac.media(empty).count() == 0


# ---- 9 ------------------------------------------------------------------------------------------------------

def bag(text, n=5):
    w = [x for x in re.split("[ \t-\r]+", text.lower().strip(" \t\n\v\f\r")) if x]
    return Counter(tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))) if w else Counter()


def test_samples_collide_as_often_as_bags_are_alike(spark):
    a, b = "p p p p q q r s t u v w", "p p q q q q r s t x y z"
    df = spark.createDataFrame([(0, a), (1, b), (2, a)], "k long, text string")
    got = {r["k"]: r["fingerprint"] for r in fingerprint.fingerprints(df, ["k"], words=1, repeats=300, slots=1).collect()}
    x, y = bag(a, 1), bag(b, 1)
    same = sum(got[0][i : i + 4] == got[1][i : i + 4] for i in range(0, 1200, 4)) / 300
    assert got[0] == got[2] and same == pytest.approx(sum((x & y).values()) / sum((x | y).values()), abs=0.09)


def test_heavy_shingles_count_in_every_slot(spark):
    pairs = [(["x"] * 1000, 10), (["x"] * 300 + ["y"] * 200, 100), (["x"] * 40, 120)]
    rows = [(2 * i + j, " ".join(shared + [f"{own}{k}" for k in range(many)])) for i, (shared, many) in enumerate(pairs) for j, own in enumerate("ab")]
    made = fingerprint.fingerprints(spark.createDataFrame(rows, "k long, text string"), ["k"], words=1)
    a, b = made.where("k % 2 = 0").withColumn("k", F.col("k") + 1).withColumnRenamed("fingerprint", "f"), made
    got = {r["k"]: r["like"] for r in a.join(b, "k").select("k", fingerprint.likeness(F.col("f"), F.col("fingerprint")).alias("like")).collect()}
    for i in range(len(pairs)):
        x, y = bag(rows[2 * i][1], 1), bag(rows[2 * i + 1][1], 1)
        assert got[2 * i + 1] == pytest.approx(sum((x & y).values()) / sum((x | y).values()), abs=0.17)


def test_fingerprint_query(docs, empty):
    got = by_id(fingerprint.near(docs))
    order, texts = sorted(got), {i: t or "" for i, t, *_ in ROWS}
    off = []
    for i, j in zip(order, order[1:] + order[:1], strict=True):
        t, cut = texts[i], len(texts[i]) // 4
        edited = t[: len(t) - cut] + texts[j][:cut]
        assert got[i]["n_chars"] == len(t) and got[i]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        a, b = bag(t), bag(edited)
        off.append(abs(got[i]["near_edited"] - (sum((a & b).values()) / sum((a | b).values()) if a or b else 1)))
        assert 0 <= got[i]["near_next"] <= 1
    assert sum(off) / len(off) < 0.12 and got[1000]["fingerprint"] == got[1002]["fingerprint"]
    assert fingerprint.near(empty).count() == 0 and fingerprint.near(docs.union(docs)).count() == 2 * len(ROWS)


def test_successors_over_gaps(spark, monkeypatch):
    monkeypatch.setattr(fingerprint, "SPAN", 4)
    keys = [0, 1, 5, 17, 18, 90, 400, 401, 5000, 70_000]
    got = dict(fingerprint.successors(spark.createDataFrame([(k,) for k in keys], "b long"), "b").collect())
    assert got == dict(zip(keys, [*keys[1:], None], strict=True))


# ---- 10 -----------------------------------------------------------------------------------------------------

def test_pieces_are_the_tokenizers(docs):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    t, capacity = Tokenizer.from_file(path), 100
    got = {(r["doc_id"], r["piece"]): r for r in packing.pieces(docs, path, capacity).collect()}
    want = {}
    for i, text, *_ in ROWS:
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 0]
        for p, s in enumerate(range(0, len(ids), capacity)):
            want[i, p] = (s, len(ids[s : s + capacity]), zlib.crc32(np.array(ids[s : s + capacity], "<u4").tobytes()))
    assert {k: (r["start"], r["length"], r["ids_crc32"]) for k, r in got.items()} == want


@pytest.mark.parametrize("seed", range(3))
def test_packing_is_tight(seed):
    rng = random.Random(seed)
    hist = Counter(rng.choice([rng.randint(1, 300), rng.randint(1, 2048), 2048]) for _ in range(800))
    places, bins = packing.plan(dict(hist), 2048)
    fill, seen = Counter(), Counter()
    for length, low_, high, first, each, _ in places:
        seen[length] += high - low_
        for r in range(high - low_):
            fill[first + r // each] += length
    assert seen == hist and max(fill.values()) <= 2048 and len(fill) == bins
    assert bins <= -(-sum(k * n for k, n in hist.items()) // 2048) + 1
    assert packing.plan({}, 10) == ([], 0)


def test_completion_is_the_best():
    """Against all fillings, on small bins."""
    rng = random.Random(6)

    def best(counts, free):
        sums = {0}
        for x in np.flatnonzero(counts).tolist():
            sums = {s + x * k for s in sums for k in range(int(counts[x]) + 1) if s + x * k <= free}
        return max(sums)

    for _ in range(100):
        counts = np.zeros(41, np.int64)
        for _ in range(rng.randint(0, 6)):
            counts[rng.randint(3, 25)] += rng.randint(1, 2)
        largest = rng.randint(10, 40)
        assert sum(packing.fill(counts, largest, 40)) == best(counts[: 40 - largest + 1], 40 - largest)


def test_packed_rows(docs, empty):
    from intervalnav.llm.queries_packing import packed

    out = packed(docs).collect()
    by_bin = {}
    for r in out:
        by_bin.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for spans in by_bin.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= 2048
    assert len({(r["doc_id"], r["piece"]) for r in out}) == len(out) and packed(empty).count() == 0


# ---- pipeline -----------------------------------------------------------------------------------------------

def test_pipeline_stages(spark, tmp_path):
    import corpus_pipeline as cp

    path = str(tmp_path / "documents.parquet")
    spark.createDataFrame([r[:5] for r in ROWS], SCHEMA.rsplit(", score", 1)[0]).write.parquet(path)
    docs = spark.read.parquet(path)
    out = []
    for k, (_, stage) in enumerate(cp.STAGES):
        stage(spark, docs, str(tmp_path)).write.parquet(str(tmp_path / f"s{k}"))
        docs = spark.read.parquet(str(tmp_path / f"s{k}"))
        out.append(docs)
    assert all(d.columns == ["doc_id", "text", "lang", "source", "n_chars"] for d in out[:3])
    texts = {i: t for i, t, *_ in ROWS}
    first = {r["doc_id"]: r["text"] for r in out[0].collect()}
    assert set(first) <= {i for i, t in texts.items() if any(c.isalpha() for c in t or "")} and {i for i in texts if i < 60} <= set(first)
    second = {r["doc_id"]: r["text"] for r in out[1].collect()}
    want = brute_components(list(second.items()))
    assert {r["doc_id"] for r in out[2].collect()} == {i for i in second if want[i][1] == i}
    assert {r["doc_id"] for r in out[3].select("doc_id").distinct().collect()} == {r["doc_id"] for r in out[2].collect()}
    assert cp.run(spark, str(tmp_path)).count() == out[3].count()


def test_pipeline_near_copies_are_alike_in_five_words(spark):
    import corpus_pipeline as cp

    rows = []
    for g, (size, changes) in enumerate([(53, [20]), (53, [3]), (110, [20, 80]), (45, [20]), (30, []), (60, [20, 40])]):
        base = [f"w{g}x{i}" for i in range(size)]
        rows += [(len(rows), " ".join(base), "xx", "s", 0), (len(rows) + 1, " ".join("new" if i in changes else w for i, w in enumerate(base)), "xx", "s", 0)]
    docs = spark.createDataFrame(rows, SCHEMA.rsplit(", score", 1)[0])
    want, strict = brute_components(rows, 5, 80), brute_components(rows)
    assert {i for i in want if want[i][1] != i} == {1, 3, 5, 9} and {i for i in strict if strict[i][1] != i} == {9}
    assert {r["doc_id"] for r in cp.without_near_copies(spark, docs, "").collect()} == {i for i in want if want[i][1] == i}
