"""The ten operators against brute force on small fixtures: nulls, ties, repeats, empty tables, extra columns."""

import hashlib
import html
import html.parser
import os
import random
import re
import struct
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from edgesketch.llm import classifier, decontam, html_text, jaccard, packing, quality_rules, suffix_dedup, token_files, tokens, url_filter
from edgesketch.llm import textkit as K
from edgesketch.llm.common import Sieve, shared_dir
from edgesketch.llm.components import connected
from edgesketch.plans import tasks

GIVEN = "/root/testdata/sf0.01"
WORDS = "the of and to in is that it was for on are with as his they at be this from".split()


def prose(rng, n):
    return " ".join(rng.choice(WORDS) + str(rng.randint(0, 60)) for _ in range(n))


def fixture(seed=1):
    """Texts with copies, near copies, shared passages, nulls, empties, odd characters and one long text."""
    rng = random.Random(seed)
    passage, line = prose(rng, 70), "Licensed under the Example License, Version 2."
    texts = [prose(rng, rng.randint(1, 120)) for _ in range(40)]
    texts += [texts[3], texts[3], texts[4], texts[5] + " tail", "x " + texts[5]]
    texts += [prose(rng, 30) + " " + passage + " " + prose(rng, 30) for _ in range(4)]
    texts += [line + "\n" + prose(rng, 40) for _ in range(6)]
    texts += [None, "", " \n\t ", "a", "é" * 50, "ab " * 400, "Ñandú 'tis <|endoftext|> it's\u3000done \U0001f600", "MiXed CASE " * 8, prose(rng, 6000)]
    return [(i, t) for i, t in enumerate(texts)]


def frame(spark, rows, source=lambda i: f"src{i % 3}"):
    data = [(i, t, "en", source(i), len(t) if t is not None else None, "extra", 1, "x", None, 2) for i, t in rows]
    clashing = "spans string, cut int, kept string, did long, component_id int"
    return spark.createDataFrame(data, "doc_id long, text string, lang string, source string, n_chars long, " + clashing).repartition(3)


@pytest.fixture(scope="module")
def docs(spark):
    return frame(spark, fixture()).cache()


def empty(spark):
    return frame(spark, [])


# ---------------------------------------------------------------- op1

WORD = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")


def low(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def brute_contamination(rows, items, width=10):
    grams = {}
    for item, t in items:
        w = WORD.findall(low(t))
        n = min(width, len(w))
        for i in range(len(w) - n + 1 if n else 0):
            grams.setdefault(tuple(w[i : i + n]), set()).add(str(item))
    out = {}
    for d, t in rows:
        w = WORD.findall(low(t))
        hit, found = set(), set()
        for n in {len(g) for g in grams}:
            for i in range(len(w) - n + 1):
                if tuple(w[i : i + n]) in grams:
                    hit |= set(range(i, i + n))
                    found |= grams[tuple(w[i : i + n])]
        out[d] = (len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit))
    return out


@pytest.mark.parametrize("block", [decontam.BLOCK_BYTES, 300])
def test_decontamination(spark, docs, block):
    rows = fixture()
    items = [(0, " ".join(rows[7][1].split()[5:30])), (1, "THE0 of1"), (2, None), (3, "!!"), (4, rows[60][1]), (5, "a"), (11, rows[7][1]), (5, "mixed-case")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {r.doc_id: tuple(r)[1:6] for r in decontam.scan(docs, bench, block_bytes=block).collect()}
    assert got == brute_contamination(rows, items)
    left = decontam.decontaminate(docs, bench, block_bytes=block)
    assert left.columns == docs.columns
    after = brute_contamination([(r.doc_id, r.text) for r in left.collect()], items)
    gone = {d for d, x in got.items() if 2 * x[1] > x[0]}
    assert set(after) == set(got) - gone and sum(x[1] for x in after.values()) == 0
    assert decontam.scan(empty(spark), bench).isEmpty()
    assert decontam.scan(docs, bench.limit(0)).where("contaminated").isEmpty()


# ---------------------------------------------------------------- op2


def brute_pack(sizes, lengths, fixed, attention):
    best = None
    for most in lengths:
        bins, rooms = [], []
        for t, s in enumerate(sizes):
            fit = [(rooms[k][0], -rooms[k][1], k) for k in range(len(bins)) if rooms[k][0] >= s]
            if fit:
                k = min(fit)[2]
            else:
                can = [c for c in lengths if c <= most and c >= s] or [min(c for c in lengths if c >= s)]
                c = min(can, key=lambda c: (packing.cost(c, fixed, attention) / c, c))
                k = len(bins)
                bins.append([])
                rooms.append((c, t))
            bins[k].append(t)
            rooms[k] = (rooms[k][0] - s, t)
        fitted = [min(c for c in lengths if c >= sum(sizes[t] for t in b)) for b in bins]
        total = sum(packing.cost(c, fixed, attention) for c in fitted)
        if best is None or total < best[2]:
            best = bins, fitted, total
    return best


def test_packing_equals_brute_force():
    rng = random.Random(4)
    for _ in range(25):
        lengths = (8, 16, 40)
        sizes = sorted((rng.randint(1, 40) for _ in range(rng.randint(0, 60))), reverse=True)
        places, fitted, total = packing.pack_shard(sizes, lengths, 2.0, 100.0)
        bins, wanted, least = brute_pack(sizes, lengths, 2.0, 100.0)
        assert fitted == wanted and total == least
        for k, b in enumerate(bins):
            at = 0
            for t in b:
                assert places[t] == (k, at)
                at += sizes[t]


def test_packing_places_all_tokens(spark, docs):
    sized = packing.token_sizes(docs).cache()
    assert sized.where("doc_id IN (55, 56)").agg(F.max("n_tokens")).first()[0] == 1 and sized.where("n_tokens < 1").isEmpty()
    got = packing.pack(sized, (64, 128, 256), shard_weight=4000).toPandas()
    assert (got.groupby("doc_id").length.sum().sort_index() == sized.toPandas().groupby("doc_id").n_tokens.sum().sort_index()).all()
    for (_, size), b in got.sort_values("offset").groupby(["bin_id", "bin_length"]):
        assert (b.offset.values == np.concatenate([[0], b.length.cumsum().values[:-1]])).all() and b.length.sum() <= size
        assert size == 64 or b.length.sum() > size // 2
    assert packing.pack_documents(empty(spark)).isEmpty()


# ---------------------------------------------------------------- op3


def brute_quality(rows, source, limit, least_left=10):
    words = lambda t: re.findall("[^\x20\x09-\x0d]+", t or "")
    norm = lambda x: re.sub("[0-9]+", "0", x).lower().strip(" \t\n\x0b\x0c\r")
    texts, first = {}, {}
    for d, t in rows:
        for x in {norm(x) for x in (t or "").split("\n")} - {""}:
            texts.setdefault((source(d), x), set()).add(t)
            first[source(d), x] = min(d, first.get((source(d), x), d))
    out = {}
    for d, t in rows:
        w = words(t)
        grams = [tuple(w[i : i + 8]) for i in range(len(w) - 7)]
        places = {p for i, g in enumerate(grams) if grams.count(g) > 1 for p in range(i, i + 8)}
        full = [x for x in (t or "").split("\n") if words(x)]
        lost = sum(len(words(x)) for x in map(norm, (t or "").split("\n")) if x and len(texts[source(d), x]) > limit and first[source(d), x] != d)
        bad = len(w) < 20 or 100 * len(places) > 30 * len(w)
        left = len(w) - lost
        out[d] = (len(w), sum(map(len, w)), len(re.findall("[#*$%&|<>]", t or "")), len(full) - len(set(full)), len(places), bad, not bad and left >= least_left and 2 * left >= len(w))
    return out


def test_quality_rules(spark):
    rng = random.Random(2)
    rows = [r for r in fixture() if r[1] is None or len(r[1]) < 5000]
    rows += [(100 + i, "Shared line of words\n" + prose(rng, 25) + f"\n#{i} | page {i}\n" + "x y\n" * (i % 3)) for i in range(12)]
    rows += [(130, prose(rng, 12) + "\n\n" + "Shared line of words\n" * 4), (131, "one two three four five six seven eight " * 5)]
    source = lambda i: None if i % 4 == 0 else "s"
    df = frame(spark, rows, source)
    expected = brute_quality(rows, source, 3)
    got = quality_rules.judge(df, line_limit=3).select(*quality_rules.FIGURES)
    assert {r.doc_id: tuple(r)[1:] for r in got.collect()} == expected
    kept = quality_rules.apply(df, line_limit=3)
    assert kept.columns == df.columns
    texts = {r.doc_id: r.text for r in kept.collect()}
    assert set(texts) == {d for d, x in expected.items() if x[-1]}
    assert sum("Shared line" in t for d, t in texts.items() if d % 4) == 1
    assert quality_rules.judge(empty(spark)).isEmpty() and quality_rules.apply(empty(spark)).isEmpty()
    twice = quality_rules.judge(df.union(df), line_limit=3)
    assert twice.count() == 2 * len(rows)


def test_quality_rules_search_long_lists_of_lines(spark):
    rng = random.Random(4)
    shared = [f"shared {prose(rng, 3)}" for _ in range(201)]
    rows = [(i, "\n".join(x for j, x in enumerate(shared) if (i + j) % 5) + "\n" + prose(rng, 600)) for i in range(9)]
    source = lambda i: "s"
    df = frame(spark, rows, source)
    got = quality_rules.judge(df, line_limit=3)
    assert {r.doc_id: tuple(r)[1:] for r in got.select(*quality_rules.FIGURES).collect()} == brute_quality(rows, source, 3)
    assert got.agg(F.max(F.size("cut"))).first()[0] > 128
    assert sum(r.text.count("shared ") for r in quality_rules.apply(df, line_limit=3).collect()) == 201


# ---------------------------------------------------------------- op4


def brute_url(url):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    host = re.match("[^/?#]*", rest)[0]
    path = re.match("[^?#]*", rest[len(host) :])[0]
    host = low(host)
    fit = [r for r in url_filter.SITE_RULES if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    if fit:
        best = min(fit, key=lambda r: (-len(r.name), r.name))
        return host, path, best.name, best.verdict
    return host, path, None, "block" if url and any(re.search(p.pattern, url.lower()) for p in url_filter.PATTERNS) else "allow"


def test_url_filters(spark):
    urls = [None, "", "no scheme", "http://", "HTTP://Example.COM/en/7?x", "https://a.example.com/en/71", "https://a.example.com/EN/7", "http://badexample.com/en/7", "http://x.com/en/", "http://x.com/en", "http://net/de/8",
            "http://example.net/de/8#f", "http://a.example.net:80/de/8", "http://q.org/es/?a=http://b.com/en/", "http://h.io/wp-login.php", "http://ads.h.io/x", "http://h.io/cart?x=1", "http://h.io/a://b.com/en/", "ftp://com/en/x", "http://net/",
            "http://h.io/?print=1", "http://a.xxx/", "http://org/es/" + "y" * 5000, "http://h.io/en/\nx"]
    rng = random.Random(3)
    urls += [f"{rng.choice(['http', 'https'])}://{rng.choice(['', 'm.', 'blog.'])}{rng.choice(['example.com', 'example.net', 'a.org', 'com', 'net'])}/{rng.choice(['en', 'de', 'es', 'fr'])}/{rng.randint(0, 99)}{rng.choice(['', '?a=1', '#t'])}" for _ in range(200)]
    df = spark.createDataFrame([(i, u, "z", "h") for i, u in enumerate(urls)], "page_id long, url string, rule string, host string")
    got = {r.page_id: tuple(r)[1:] for r in url_filter.judge(df.select("page_id", "url", "rule")).collect()}
    assert got == {i: brute_url(u) for i, u in enumerate(urls)}
    assert url_filter.judge(df.union(df)).count() == 2 * len(urls) and url_filter.judge(df.limit(0)).isEmpty()


def test_rules_are_indexed_by_their_rarest_token(spark):
    seen = spark.createDataFrame([("com",)] * 5 + [("en",)] * 2 + [("example",)] * 3, "token string")
    rules = url_filter.rule_table(spark)
    by = {r.rule: r.token for r in url_filter.index(rules, seen).collect()}
    assert by["com/en/"] == "en" and by["example.com/en/7"] == "en" and by["net/de/"] == "de" and by["basket"] == ""


# ---------------------------------------------------------------- op5


def brute_spans(rows, length):
    bodies = [(t or "").encode() for _, t in rows]
    seen = {}
    for k, b in enumerate(bodies):
        for i in range(len(b) - length + 1):
            seen.setdefault(b[i : i + length], []).append((k, i))
    cover = [np.zeros(len(b), bool) for b in bodies]
    for v in seen.values():
        if len(v) > 1:
            for k, i in v:
                cover[k][i : i + length] = True
    out = {}
    for (d, _), b, c in zip(rows, bodies, cover):
        runs = int((np.diff(np.concatenate([[0], c.astype(int)])) == 1).sum())
        out[d] = (len(b), int(c.sum()), runs, hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~c])).hexdigest())
    return out


@pytest.mark.parametrize(("length", "most"), [(40, 20_000), (120, 20_000), (40, 2), (400, 20_000), (9, 20_000)])
def test_suffix_dedup(spark, docs, length, most):
    rows = fixture() if length > 9 else [r for r in fixture() if r[1] is None or len(r[1]) < 300]
    df = docs if length > 9 else frame(spark, rows)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.spans(df, length, most).collect()}
    assert got == brute_spans(rows, length)


def test_suffix_parts(spark, docs):
    rng = random.Random(5)
    strings = list({bytes(rng.choice(b"ab") for _ in range(rng.randint(0, 12))) for _ in range(200)})
    order, lcp = suffix_dedup.BlindTrie(strings).walk()
    assert [strings[i] for i in order] == sorted(strings)
    assert all(n == suffix_dedup.common_prefix(strings[a], strings[b]) for a, b, n in zip(order, order[1:], lcp[1:]))
    # the sweep over many surroundings equals the matrix over few
    many = [bytes(rng.choice(b"ab") for _ in range(30)) for _ in range(90)]
    lefts, rights = [m[:12] for m in many], [m[12:] for m in many]
    whole = suffix_dedup.reaches(lefts, rights, 20)
    for i in range(90):
        pairs = [(min(suffix_dedup.common_prefix(lefts[i], lefts[j]), 12), suffix_dedup.common_prefix(rights[i], rights[j])) for j in range(90) if j != i]
        good = [(a, b) for a, b in pairs if a + b >= 20]
        assert whole[i] == ((max(a for a, _ in good), max(b for _, b in good)) if good else None)
    data = np.frombuffer(prose(rng, 4000).encode(), np.uint8)
    was, suffix_dedup.STRETCH = suffix_dedup.STRETCH, 1000
    try:
        at, _ = suffix_dedup.anchors_of_long(data, 50)
    finally:
        suffix_dedup.STRETCH = was
    assert at.tolist() == sorted(set(suffix_dedup.anchors_of(data, np.array([0, len(data)]), 50)[1].tolist()))
    left = suffix_dedup.apply(docs, 120)
    assert left.columns == docs.columns and left.where("doc_id IN (3, 40, 41)").isEmpty() and left.where("text IS NULL").count() == 1
    assert suffix_dedup.spans(empty(spark)).isEmpty() and suffix_dedup.apply(empty(spark)).isEmpty()


# ---------------------------------------------------------------- op6, op8


@pytest.fixture(scope="module")
def library():
    return tokens.shared(tokens.vocabulary_path()).library


@pytest.mark.parametrize("planes", ["byte", "bit"])
def test_token_files_round_trip(spark, docs, library, planes, tmp_path):
    path = str(tmp_path / "ids")
    token_files.write(docs, path, planes=planes, block_ids=100, segment_ids=500)
    got = {r.doc_id: tuple(r)[1:] for r in token_files.digests(spark, path).collect()}
    at = 0
    for d, t in fixture():
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 2]
        assert got[d] == (at, len(ids), zlib.crc32(struct.pack(f"<{len(ids)}I", *ids)))
        at += len(ids)
    r = token_files.segments(spark, path).orderBy("file_no", "segment").first()
    one = token_files.unpack_block(r.payload, r.plane_at, 0, r.n_ids, planes, 100)
    assert (one == token_files.unpack_ids(r.payload, r.plane_at, r.n_ids, planes, 100)[: len(one)]).all()


def test_repeated_rows_and_empty_tables(spark, library, tmp_path):
    rows = fixture()[:6]
    rows += rows[:4] + [(2, "another text under the same id"), (None, "no id"), (None, None)]
    twice = frame(spark, rows, lambda i: "src")
    key = lambda x: (x is not None, x or 0)
    size = lambda t: len(library.encode(t or "", add_special_tokens=False).ids)
    token_files.write(twice, str(tmp_path / "twice"), segment_ids=50)
    got = sorted(((r.doc_id, r.start, r.n_tokens) for r in token_files.digests(spark, str(tmp_path / "twice")).collect()), key=lambda r: r[1])
    assert [d for d, _, _ in got] == sorted((d for d, _ in rows), key=key)
    assert [a for _, a, _ in got] == [0, *np.cumsum([n for _, _, n in got])[:-1].tolist()]
    assert sorted(n for _, _, n in got) == sorted(size(t) + 1 for _, t in rows)
    counted = [(r.doc_id, r.n_tokens) for r in tokens.token_counts(twice).collect()]
    assert sorted(counted, key=str) == sorted(((d, size(t)) for d, t in rows), key=str)
    bench = spark.createDataFrame([(0, rows[1][1]), (0, rows[1][1])], "item_id long, text string")
    hits = [(r.doc_id, r.n_items) for r in decontam.scan(twice, bench).collect()]
    assert len(hits) == len(rows) and hits.count((1, 1)) == 2 and sum(n for _, n in hits) == 2
    packed = packing.pack(packing.token_sizes(twice), (64, 128, 256))
    assert packed.agg(F.sum("length")).first()[0] == packing.token_sizes(twice).agg(F.sum("n_tokens")).first()[0]
    token_files.write(empty(spark), str(tmp_path / "none"))
    assert token_files.digests(spark, str(tmp_path / "none")).isEmpty()


def test_planes():
    ids = np.array([0, 1, 50256, 2**32 - 1, 7] * 31, "<u4")
    for planes in ("byte", "bit"):
        assert (token_files.from_planes(token_files.to_planes(ids, planes), len(ids), planes) == ids).all()
        payload, at = token_files.pack_ids(ids, planes, 16)
        assert (token_files.unpack_ids(payload, at, len(ids), planes, 16) == ids).all()
        assert token_files.pack_ids(ids[:0], planes) == (b"", [0])


def test_token_counts(spark, docs, library):
    got = {r.doc_id: tuple(r)[1:] for r in tokens.token_counts(docs, limit=200).collect()}
    for d, t in fixture():
        n = len(library.encode(t or "", add_special_tokens=False).ids)
        assert got[d] == (len((t or "").encode()), n, n > 200)
    assert tokens.token_counts(empty(spark)).isEmpty()


def test_pre_tokens_equal_the_library(library):
    rng = random.Random(6)
    pieces = ["'s", "'ll", "'re", "'", " ", "  ", "\n", "\t", "a", "ré", "7", "!", "é", "e\u0301", "中", "\xa0", "<|endoftext|>", "ſ", "\x1c", "\x85", "𝔘", "s", "ve", "'ve", "'d", "D", "\u2003", "😀", "٣", "½"]
    texts = ["".join(rng.choice(pieces) for _ in range(rng.randint(0, 30))) for _ in range(3000)] + [None, ""]
    coder = tokens.Coder(tokens.shared(tokens.vocabulary_path()), remembered=60_000)
    for at in range(0, len(texts), 500):
        ids, n = coder.encode(texts[at : at + 500])
        wanted = [library.encode(t or "", add_special_tokens=False).ids for t in texts[at : at + 500]]
        assert n.tolist() == [len(x) for x in wanted] and ids.tolist() == [i for x in wanted for i in x]


# ---------------------------------------------------------------- op7


def test_html_extraction(spark):
    article = "<article><h1>A &amp; B</h1><p><b>One\n two<br>three<p>x &lt; y &#233;<script>var t='</p>'</script><div class='ad'>buy</div><section class=\"comments\"><p>nice!</p></section><ul><li>l1<li>l2</ul></article>"
    wrap = "<html><head><title>T</title><style>p{{}}</style></head><body><header>site</header><nav><ul><li>n</li></ul></nav><!-- <p>no</p> -->{}<footer>f &copy;</footer></body>"
    expected = "A & B\n\nOne two three\n\nx < y é\n\nl1\n\nl2"
    menu = "<div>home news sport weather shop travel food style</div>"
    unique = [f"<div>{menu}<p>unique words number {i} of this page {i * 7} stay</p></div>" for i in range(4)]
    rows = [(0, "http://a.b/x", wrap.format(article)), (1, "http://a.b/x", None), (2, None, ""), (3, "u", "plain  text &amp; more"), (4, "http://c.d/", "<p>un<script>x"), (5, "http://c.d/", "<main><p>m</p></main><p>out</p>")]
    rows += [(10 + i, "http://same.host/p", f"<body>{u}</body>") for i, u in enumerate(unique)] + [(20, "http://same.host/q", f"<body>{unique[0]}</body>"), (21, "http://other.host/", f"<body>{unique[0]}</body>")]
    df = spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, text string").repartition(3)
    got = {r.page_id: (r.url, r.text, r.n_chars) for r in html_text.extract(df).collect()}
    assert got[0] == ("http://a.b/x", expected, len(expected))
    assert got[1][1] == got[2][1] == "" and got[3][1] == "plain text & more" and got[4][1] == "un" and got[5][1] == "m"
    for i in range(1, 4):
        assert got[10 + i][1] == f"unique words number {i} of this page {i * 7} stay"
    assert "home news" in got[21][1]  # one page of its host: nothing is repeated
    assert got[20][1] == got[10][1]  # a copy of a page does not make the page its own boilerplate
    assert html_text.extract(df.union(df)).count() == 2 * len(rows) and html_text.extract(df.limit(0)).isEmpty()
    assert html.unescape("&copy;") == "©"


def test_html_undeclared_text_beside_a_container(spark):
    menu = "<div>home news sport weather shop travel food style</div>"
    page = "<body>{}<article><p>teaser {}</p></article><p>the story of page {} stands {} words away from its card</p></body>"
    rows = [(i, "http://one.host/", page.format(menu, i, i, i * 7)) for i in range(5)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    got = {r.page_id: r.text.split("\n") for r in html_text.extract(df).collect()}
    for i in range(5):
        assert [x for x in got[i] if x] == [f"teaser {i}", f"the story of page {i} stands {i * 7} words away from its card"]


class _Reader(html.parser.HTMLParser):
    """An independent reader: the text of article elements, split where a block element starts or ends."""

    BLOCK = "article p h1 h2 h3 h4 h5 h6 ul ol li div section header footer aside nav form table tr td th blockquote pre figure figcaption dl dt dd hr"
    OUT = "script style nav aside footer form header"

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.inside, self.out, self.parts, self.found = 0, [], [], []

    def flush(self):
        text = " ".join("".join(self.parts).split())
        self.parts = []
        if text and self.inside and not self.out:
            self.found.append(text)

    def handle_starttag(self, tag, attrs):
        if tag in self.BLOCK.split():
            self.flush()
        if tag == "article":
            self.inside += 1
        elif self.inside and (tag in self.OUT.split() or self.out and tag == self.out[0] or not self.out and html_text.ASIDE_WORDS & set((dict(attrs).get("class") or "").split())):
            self.out.append(tag)
        elif tag == "br":
            self.parts.append(" ")

    def handle_endtag(self, tag):
        if tag in self.BLOCK.split():
            self.flush()
        if self.out and tag == self.out[0]:
            self.out.pop()
        elif tag == "article":
            self.inside -= 1

    def handle_data(self, data):
        if self.inside and not self.out:
            self.parts.append(data)


def test_html_of_the_given_pages_equals_an_independent_reader(spark):
    pages = spark.read.parquet(GIVEN + "/pages.parquet")
    got = {r.page_id: r for r in html_text.extract(pages).collect()}
    assert len(got) == pages.count()
    many = 0
    for r in pages.collect():
        reader = _Reader()
        reader.feed(r.html or "")
        reader.flush()
        text = "\n\n".join(reader.found)
        many += len(reader.found) > 1
        assert (got[r.page_id].text, got[r.page_id].n_chars, got[r.page_id].url) == (text, len(text), r.url)
    assert many > 100


def test_html_rests_on_the_suffix_array(spark, monkeypatch):
    menu = "<div>home news sport weather shop travel food style</div>"
    rows = [(i, "http://one.host/", f"<body>{menu}<p>the story number {i} stands {i * 7} words away from its menu</p></body>") for i in range(4)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    assert all("home news" not in r.text for r in html_text.extract(df).collect())
    monkeypatch.setattr(html_text, "repeated_runs", lambda parsed, run: spark.createDataFrame([], "host string, h long"))
    assert all("home news" in r.text for r in html_text.extract(df).collect())


def test_html_undeclared_block_that_repeats_the_article_of_another_page(spark):
    story = "storm floods the valley and many roads are closed until monday"
    rows = [(1, "http://one.host/", f"<article><p>{story}</p></article>"), (2, "http://one.host/", f"<article><p>own text</p></article><div>{story}</div><p>some words that only the second page of this host has</p>")]
    rows += [(3, "http://two.host/", rows[1][2]), (4, "http://three.host/", f"<article><p>{story}</p></article><div>{story}</div>"), (5, "http://one.host/", f"<article><h1>copy</h1><p>{story}</p></article>")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(4)
    got = {r.page_id: r.text.split("\n\n") for r in html_text.extract(df).collect()}
    assert got[1] == [story] and got[5] == ["copy", story]  # a declared article is kept whole
    assert got[2] == ["own text", "some words that only the second page of this host has"]
    assert got[3] == ["own text", story, "some words that only the second page of this host has"]  # another host
    assert got[4] == [story, story]  # of one page


def test_html_three_blocks(spark):
    df = spark.createDataFrame([(1, "http://a.b/", "<article><p>one</p><p>two\n words</p><div>three</div></article>")], "page_id long, url string, html string")
    assert html_text.extract(df).first().text == "one\n\ntwo words\n\nthree"


def test_sorted_suffixes():
    rng = random.Random(7)
    page = np.sort(np.array([rng.randint(0, 5) for _ in range(200)]))
    t = np.array([rng.randint(0, 2) for _ in range(200)], np.uint64)
    order, rank = html_text.sorted_suffixes(t, page, 5)
    key = [tuple(t[j] for j in range(i, min(200, i + 5)) if page[j] == page[i]) for i in range(200)]
    assert [key[i] for i in order] == sorted(key)
    assert all((rank[i] == rank[j]) == (key[i] == key[j]) for i in range(200) for j in range(0, 200, 7))


# ---------------------------------------------------------------- op9


def brute_links(rows, width, percent):
    sets = {}
    for d, t in rows:
        w = re.findall("[^\x20\x09-\x0d]+", low(t))
        n = min(width, len(w))
        sets[d] = {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if n else set()
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    names = sorted(sets)
    for i, a in enumerate(names):
        for b in names[:i]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), find(d)) for d in sets}


def near_fixture():
    rng = random.Random(8)
    rows = fixture(9)
    base = prose(rng, 90).split()
    for i in range(40):  # a chain of drifting copies, and a star of them
        base[rng.randrange(90)] = f"new{i}"
        rows.append((200 + i, " ".join(base)))
    star = prose(rng, 60)
    rows += [(300 + i, star + f" end{i}" + (" more" * (i % 4))) for i in range(30)]
    rows += [(400 + i, f"{star} " + prose(rng, 200)) for i in range(8)]
    return rows


@pytest.mark.parametrize(("width", "percent", "frequent", "most"), [(4, 85, 32, 20_000), (5, 80, 2, 20_000), (4, 60, 4, 5), (2, 90, 3, 8)])
def test_jaccard_join(spark, width, percent, frequent, most):
    rows = near_fixture()
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.classes(frame(spark, rows), width, percent, frequent, most).collect()}
    assert got == brute_links(rows, width, percent)


def test_jaccard_keep_one_and_region(spark, docs):
    kept = jaccard.keep_one(docs.union(docs.where("doc_id < 5")))
    wanted = {d for d, (_, c) in brute_links(fixture(), 5, 80).items() if c == d}
    assert sorted(r.doc_id for r in kept.collect()) == sorted(wanted) and kept.columns == docs.columns
    assert jaccard.classes(empty(spark)).isEmpty()
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**62, 60).astype(np.uint64)
    sets = [np.unique(np.where(rng.random(60) < 0.08, rng.integers(0, 2**62, 60).astype(np.uint64), base)) for _ in range(500)]
    region = jaccard.Region(np.arange(500), sets, 85)
    region.solve(np.arange(500))
    lookup = [set(s.tolist()) for s in sets]
    comp = list(range(500))
    for i in range(500):
        for j in range(i):
            both = len(lookup[i] & lookup[j])
            if 100 * both >= 85 * (len(lookup[i]) + len(lookup[j]) - both) and comp[i] != comp[j]:
                old, new = comp[i], comp[j]
                comp = [new if c == old else c for c in comp]
    assert len({(a, b) for a, b in zip(comp, region.comp.tolist())}) == len(set(comp)) == len(set(region.comp.tolist()))


def test_jaccard_keep_one_decides_by_row(spark):
    rng = random.Random(12)
    a, b, c, d, e, p = (prose(rng, 60) for _ in range(6))
    rows = [(1, a), (None, a), (None, b), (None, c), (None, c), (2, d), (2, e), (3, d + " tail"), (None, ""), (None, ""), (4, ""), (2, ""), (5, p), (5, "x " + p)]
    q = prose(rng, 60)
    rows += [(None, q), (None, q + " tail")]  # linked, without a doc_id in either
    kept = [(r.doc_id, r.text) for r in jaccard.keep_one(frame(spark, rows, lambda i: "src")).collect()]
    assert sum(t in (q, q + " tail") for _, t in kept) == 1 and sum(t in (p, "x " + p) for _, t in kept) == 1
    rest = [(i, t) for i, t in kept if t not in (q, q + " tail", p, "x " + p)]
    assert sorted(rest, key=str) == sorted([(1, a), (None, b), (None, c), (2, d), (2, e), (None, ""), (4, ""), (2, "")], key=str)


def test_jaccard_classes_that_share_an_id(spark, monkeypatch):
    rows = near_fixture()
    real = jaccard.class_id
    monkeypatch.setattr(jaccard, "class_id", lambda own: (real(own)[0] % 37, real(own)[1]))
    sets = [jaccard.shingle_sets(pa.array([t], pa.string()), 4)[0] for _, t in rows]
    data = [(i, i, len(s), *jaccard.class_id(s), None, None) for (i, _), s in zip(rows, sets)]
    wide, names = jaccard.told_apart(spark.createDataFrame(data, jaccard.WIDE))
    got = {r.doc_id: r.cid for r in wide.where("n > 0").collect()}
    same = {}
    for (i, _), s in zip(rows, sets):
        if len(s):
            assert same.setdefault(s.tobytes(), got[i]) == got[i]
    assert len(set(same.values())) == len(same) and names


def test_jaccard_links_come_from_cells():
    rng = np.random.default_rng(4)
    groups = [rng.integers(0, 2**62, 60).astype(np.uint64) for _ in range(3)]
    sets = [np.unique(np.where(rng.random(60) < 0.05, rng.integers(0, 2**62, 60).astype(np.uint64), groups[i % 3])) for i in range(60)]
    region = jaccard.Region(np.arange(60), sets, 85)
    region.solve(np.arange(60))
    assert region.pivots and region.cells and not region.flat_members
    whole = jaccard.Region(np.arange(60), sets, 85)
    whole.leaf(np.arange(60))
    assert len({(a, b) for a, b in zip(region.comp.tolist(), whole.comp.tolist())}) == len(set(region.comp.tolist())) == len(set(whole.comp.tolist()))


@pytest.mark.parametrize("near", [False, True])
def test_jaccard_large_region_that_pivots_do_not_part(spark, near):
    # all at distance 1 of each other, or all near: every class is in every cell, so no turn may copy them
    rng = np.random.default_rng(2)
    base = rng.integers(0, 2**62, 40).astype(np.uint64)
    sets = [np.unique(np.concatenate([base, [i]]).astype(np.uint64) if near else rng.integers(0, 2**62, 40).astype(np.uint64)) for i in range(60)]
    rows = [(7, i, bytearray(s.tobytes())) for i, s in enumerate(sets)] + [(8, 100, bytearray(sets[0].tobytes()))]
    parted, found = jaccard._part_large(spark.createDataFrame(rows, jaccard.SETS).repartition(3), 85, 20, 10**9, rounds=1)
    got = parted.groupBy("region").count().collect()
    assert sum(r["count"] for r in got) <= 1 + 60 * 6 and max(r["count"] for r in got) < 40  # six blocks, two in a region
    together = {(a, b) for r in parted.groupBy("region").agg(F.collect_set("cid").alias("c")).collect() for a in r.c for b in r.c}
    assert all((i, j) in together for i in range(60) for j in range(60)) and (100, 100) in together
    assert found is None or found.isEmpty() != near


def test_jaccard_frequent_shingle_ties_no_strangers(spark):
    # 60 strangers with one shingle that the ranking missed: a region of all would be copied between tasks once it is large
    rng = np.random.default_rng(6)
    draw = lambda n: np.unique(np.append(rng.integers(8, 2**64, n - 1, dtype=np.uint64), np.uint64(7)))
    sets = [draw(n) for n in rng.integers(60, 1400, 60)]
    for n in (80, 1035):  # near copies, one pair on both sides of a change of the number of bins
        base = draw(n)
        sets += [base, base[: n - n // 50]]
    told = []
    for k, own in enumerate(sets):
        b = jaccard.bins_for(len(own))
        counts = np.bincount((own >> np.uint64(65 - b.bit_length())).astype(np.int64), minlength=b).astype("<u2")
        told.append((k, k, len(own), k, k, bytearray(own[: jaccard.prefix_length(len(own), 85)].tobytes()), bytearray(counts.tobytes())))
    wide, none = spark.createDataFrame(told, jaccard.WIDE), (np.zeros(0, np.uint64), np.zeros(0, np.int64))
    found = {(min(r), max(r)) for r in jaccard.candidate_links(wide, 85, 8, none).collect()}
    assert found == {(60, 61), (62, 63)}
    hub = jaccard.candidate_links(wide, 85, 8, none, hub=20).collect()
    assert {k for r in hub for k in r} == set(range(64))


def test_pipeline_keeps_no_disk_of_what_is_done(spark, monkeypatch, tmp_path):
    # shuffles of a written table, the packed pivots while their rows are paired, and all but the last stage's output are gone
    import corpus_pipeline as P

    shuffles = lambda: spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString(" ").count("/shuffle_")
    held = lambda: set(os.listdir(shared_dir(spark).removeprefix("file://") + "/edgesketch"))
    spark._jvm.System.gc()
    docs = spark.range(2000).selectExpr("id doc_id", "concat_ws(' ', id, id + 1, id + 2, id % 7, id + 3, id + 5) text")
    jaccard.materialize(docs.limit(1), "first")
    before, seen, real = shuffles(), {}, jaccard.materialize

    def told(df, tag, outer=0):
        seen[tag] = held() - old
        return real(df, tag, outer)

    old = held()
    real(docs.groupBy("text").count(), "counted")
    assert shuffles() <= before
    monkeypatch.setattr(jaccard, "materialize", told)
    jaccard.keep_one(docs).count()
    assert any(x.startswith("pivots-") for x in seen["candidates"]) and not any(x.startswith(("sets-", "classes-")) for x in seen["candidates"])
    monkeypatch.undo()
    (tmp_path / "in").mkdir()
    docs.write.parquet(f"{tmp_path}/in/documents.parquet")
    old, stages = held(), [(f"s{k}", lambda s, d, _, k=k: real(d, f"of-{k}").where(f"doc_id <> {k}")) for k in range(4)]
    monkeypatch.setattr(P, "STAGES", stages)
    assert P.run(spark, f"{tmp_path}/in").count() == 1996
    assert sorted(x.rsplit("-", 1)[0] for x in held() - old) == ["of-3", "stage-2"]


def test_sieve_loses_no_key(spark):
    keys = spark.range(0, 6000, 3).select((F.col("id") - 900).alias("key"))
    for most, passed in ((1 << 25, 2300), (64, 6000)):  # a full sieve lets all pass
        sieve = Sieve(keys.union(keys), "key", most)
        rows = spark.range(-900, 5100).select("id", F.lit("x").alias("text"))
        may = {r.id for r in sieve.may_have(rows, "id").collect()}
        without = {r.id for r in sieve.surely_without(rows, "id").collect()}
        assert may | without == set(range(-900, 5100)) and not may & without
        assert {r.key for r in keys.collect()} <= may and len(may) <= passed
    none = Sieve(keys.limit(0), "key")
    assert none.may_have(rows, "id").isEmpty() and none.surely_without(rows, "id").count() == 6000


def test_jaccard_shuffles_no_text_outside_regions(spark):
    rng, name = random.Random(21), "spark.sql.autoBroadcastJoinThreshold"
    texts = [" ".join(str(rng.random()) for _ in range(300)) for _ in range(300)]
    docs = jaccard.materialize(spark.createDataFrame([*enumerate(texts), (900, texts[7] + " tail")], "doc_id long, text string"), "given")
    wide = docs.select("doc_id", jaccard._row().alias("row"), F.col("doc_id").alias("cid"))
    regions = spark.createDataFrame([(7, 7), (900, 7)], "cid long, region long")
    ids = {i: jaccard.class_id(jaccard.shingle_sets(pa.array([t]), 4)[0]) for i, t in ((7, texts[7]), (900, texts[7] + " tail"))}
    before = spark.conf.get(name)
    spark.conf.set(name, "-1")  # as where the table of the regions' rows is large
    try:
        with tasks.measured(spark) as told:
            got = jaccard._region_sets(docs, wide, regions, 4, {v: k for k, v in ids.items()}).collect()
    finally:
        spark.conf.set(name, before)
    assert {r.cid for r in got} == {7, 900} and told.shuffle_written < 200_000 < sum(map(len, texts)) / 5


def test_jaccard_keep_one_shuffles_no_text_of_rows_that_stay(spark):
    rng, name = random.Random(22), "spark.sql.autoBroadcastJoinThreshold"
    texts = [" ".join(str(rng.random()) for _ in range(300)) for _ in range(300)]
    rows = [*enumerate(texts), (900, texts[7] + " tail"), (3, texts[3]), (None, texts[5])]
    docs = jaccard.materialize(spark.createDataFrame(rows, "doc_id long, text string"), "given")
    before = spark.conf.get(name)
    spark.conf.set(name, "-1")  # as where the tables of lost and repeated rows are large
    try:
        kept = jaccard.keep_one(docs)
        with tasks.measured(spark) as told:
            kept.write.format("noop").mode("overwrite").save()
    finally:
        spark.conf.set(name, before)
    assert sorted((r.doc_id, r.text) for r in kept.collect()) == list(enumerate(texts))
    assert told.shuffle_written < 200_000 < sum(map(len, texts)) / 5


def test_jaccard_pivots_are_bounded_by_bytes(spark):
    many = spark.createDataFrame([(1, i, bytearray(80), 4, 40.0) for i in range(4)], "region long, cid long, body binary, k long, s double")
    assert len(jaccard._pivots(many, 0, 200)[1]) == 2 and jaccard._pivots(many, 0, 79) == {}


def test_connected(spark):
    rng = random.Random(10)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(200)] + [(0, k) for k in range(300, 400)] + [(k, k + 1) for k in range(500, 560)]
    parent = {x: x for e in edges for x in e}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        x, y = find(a), find(b)
        parent[max(x, y)] = min(x, y)
    got = {r.node: r.root for r in connected(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {x: find(x) for e in edges if e[0] != e[1] for x in e}


# ---------------------------------------------------------------- op10


def test_classifier(spark):
    rng = random.Random(11)
    good = [prose(rng, rng.randint(20, 80)) for _ in range(150)]
    bad = [" ".join(w.upper() + "!!" for w in prose(rng, 40).split()) if i % 2 else " ".join([rng.choice(WORDS) + "x"] * 40) for i in range(150)]
    rows = list(enumerate(good + bad)) + [(900, None), (901, ""), (902, "  "), (903, prose(rng, 9000))]
    df = frame(spark, rows)
    labels = spark.createDataFrame([(i, int(i < 150), "en") for i in range(300)] + [(5, None, "x"), (7, 1, "x")], "doc_id long, quality int, lang string")
    got = {r.doc_id: r for r in classifier.classify(df, labels).collect()}
    assert len(got) == len(rows)
    for i, _ in rows:
        assert got[i].held_out == (zlib.crc32(str(i).encode()) % 5 == 0)
    held = [i for i in range(300) if got[i].held_out]
    assert sum(got[i].predicted == int(i < 150) for i in held) >= 0.95 * len(held)
    assert got[900].score == got[901].score == got[902].score == 0 and got[903].predicted == 1
    again = {r.doc_id: r.score for r in classifier.classify(df, labels).collect()}
    assert again == {i: r.score for i, r in got.items()}
    assert {r.score for r in classifier.classify(df, labels.limit(0)).where("doc_id < 10").collect()} == {0.5}
    assert {r.score for r in classifier.classify(df, labels.where("quality = 1")).where("doc_id < 10").collect()} == {1.0}
    assert classifier.classify(empty(spark), labels).isEmpty()


def test_classifier_of_repeated_ids(spark):
    rng = random.Random(13)
    rows = [(i, prose(rng, 20) if i % 2 else "spam " * 20) for i in range(40)] + [(i, prose(rng, 20)) for i in range(10)] + [(3, None)]
    labels = [(i, i % 2, "en") for i in range(40)] + [(i, 1 - i % 2, "en") for i in range(5)]
    told = lambda r, n: sorted((x.doc_id, x.score) for x in classifier.classify(frame(spark, r), spark.createDataFrame(n, "doc_id long, quality int, lang string")).collect())
    assert told(rows, labels) == told(rows[::-1], labels[::-1]) and len(told(rows, labels)) == len(rows)


# ---------------------------------------------------------------- kernels and the pipeline


def test_kernels():
    import pyarrow as pa

    texts = ["a bb  a", None, "", "bb a bb a", "é ü"]
    data, offsets = K.raw(pa.array(texts))
    starts, ends, first = K.words(data, offsets, K.NOT_SPACE)
    assert [data[s:e].tobytes().decode() for s, e in zip(starts, ends)] == ["a", "bb", "a", "bb", "a", "bb", "a", "é", "ü"]
    assert first.tolist() == [0, 3, 3, 3, 7, 9]
    h = K.span_hash(K.prefix_sums(data), starts, ends)
    assert h[0] == h[2] == h[4] and h[1] == h[3] and len(set(h.tolist())) == 4
    assert K.window_starts(first, 2).tolist() == [0, 1, 3, 4, 5, 7]
    assert K.covered(6, np.array([1, 2]), np.array([2, 2])).tolist() == [False, True, True, True, False, False]


def test_pipeline_against_brute_force(spark, tmp_path):
    import corpus_pipeline as P

    rng = random.Random(12)
    rows = [(i, prose(rng, rng.randint(30, 90))) for i in range(40)]
    item = prose(rng, 14)
    rows += [(50, rows[3][1]), (51, rows[4][1] + " end"), (52, "short one"), (53, prose(rng, 30) + " " + item + " " + prose(rng, 30)), (54, None)]
    passage = prose(rng, 60)
    rows += [(60 + i, prose(rng, 30) + " " + passage + " " + prose(rng, 40)) for i in range(2)]
    frame(spark, rows).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(0, item)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    docs, seen = spark.read.parquet(str(tmp_path / "documents.parquet")), []
    for k, (_, stage) in enumerate(P.STAGES):
        out = stage(spark, docs, str(tmp_path))
        out.write.parquet(str(tmp_path / f"s{k}"))
        docs = spark.read.parquet(str(tmp_path / f"s{k}"))
        seen.append({r.doc_id: r for r in docs.collect()})
        if k < 4:
            assert docs.columns == frame(spark, []).columns
    good = {d for d, x in brute_quality(rows, lambda i: f"src{i % 3}", 20).items() if x[-1]}
    assert set(seen[0]) == good and 52 not in good and 54 not in good
    assert set(seen[1]) == {d for d, (_, c) in brute_links([r for r in rows if r[0] in good], 5, 80).items() if c == d}
    cut = brute_spans([(d, r.text) for d, r in sorted(seen[1].items())], P.PASSAGE_BYTES)
    assert {d: hashlib.sha256(r.text.encode()).hexdigest() for d, r in seen[2].items()} == {d: x[3] for d, x in cut.items()}
    assert passage[20:300] not in seen[2][60].text and item in seen[2][53].text
    assert item not in seen[3][53].text and all(seen[3][d].text == r.text for d, r in seen[2].items() if d != 53)
    assert {r.doc_id for r in P.run(spark, str(tmp_path)).collect()} == set(seen[3]) == set(seen[4])
    assert docs.agg(F.sum("length")).first()[0] == packing.token_sizes(spark.read.parquet(str(tmp_path / "s3"))).agg(F.sum("n_tokens")).first()[0]


def test_pipeline_of_empty_tables(spark, tmp_path):
    import corpus_pipeline as P

    frame(spark, []).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    assert P.run(spark, str(tmp_path)).isEmpty()
