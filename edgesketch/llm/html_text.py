"""HTML extraction with a host suffix array: what a host repeats across its pages is boilerplate.

1. Each page is read once into blocks in page order, by its markup: what lies in the declared main
   container (``article``, else ``main``) is main text; menus, headers, footers, sidebars, notices,
   adverts, forms, scripts, styles and reader comments are marked as such by tag, or by a word of
   their class, id or role; the rest is undeclared.
2. The token streams of whole pages are joined by host, each as two: what is not main text, and the
   main text. Their suffixes are sorted by prefix doubling to ``run`` tokens, batch by batch; suffixes
   that share ``run`` tokens are one entry with the least and greatest page it is on. Entries meet per
   host by partial aggregates; one with two different pages is a substring repeated across distinct
   pages. Pages of equal html are one page here, so copies don't make a page its own boilerplate.
   Entries of main text alone that no undeclared block has are sieved where they are sorted.
3. An undeclared block of any page is removed if repeated runs cover at least half of its tokens, be
   it that other pages have them in their main text; unique runs stay, beside a declared container too. A declared article is kept whole, as nothing
   else may go. Only where all that a page has outside its container is under ``run`` tokens, so that
   no run can tell, the declaration decides and those few tokens go. What a declared article repeats
   (license lines, shared paragraphs) is text of the article, so runs don't decide there.
4. The blocks that stay are joined in page order by an empty line.

A host of any size is spread over the tasks: streams are cut only between pages, sorted where they
are read, and only distinct entries are shuffled, of main text those that may decide a block.

Defined results: null and empty html have an empty text; html without tags is one block; repeated
rows get a row each; an empty table gives no rows; extra columns are ignored; very long pages are
read whole; unclosed tags end with their container, an unclosed script or comment with the page;
ties do not arise.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.llm import textkit as K
from edgesketch.llm.common import Sieve, materialize, table, text_slices

RUN = 8
#: Elements whose content is no text of the page at all.
RAW = {"script", "style", "noscript", "template", "svg", "math", "iframe", "object", "canvas", "textarea", "title", "audio", "video"}
#: Elements that hold what is not the article.
ASIDE = {"nav", "aside", "footer", "form", "menu", "dialog", "select", "button", "fieldset", "datalist"}
#: Words of a class, id or role that say the same.
ASIDE_WORDS = {
    "ad", "ads", "adv", "advert", "adverts", "advertisement", "advertising", "sponsor", "sponsored", "promo", "banner", "menu", "nav", "navbar", "navigation", "breadcrumb", "breadcrumbs",
    "sidebar", "footer", "cookie", "cookies", "consent", "gdpr", "notice", "alert", "popup", "modal", "overlay", "newsletter", "subscribe", "signup", "login", "share", "sharing", "social",
    "related", "recommended", "comment", "comments", "disqus", "respond", "replies", "pagination", "pager", "toolbar", "widget", "complementary", "contentinfo", "search",
}
#: Elements that do not end a block.
INLINE = {
    "a", "abbr", "acronym", "b", "bdi", "bdo", "big", "br", "cite", "code", "data", "del", "dfn", "em", "font", "i", "img", "input", "ins", "kbd", "label", "mark", "meta", "link", "q",
    "rp", "rt", "ruby", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr", "path", "source", "picture",
}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}

_TAG = re.compile(r"<!--|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^>]*>")
_NAMES = re.compile(r"(?:class|id|role)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+)", re.I)
_CLOSE = {name: re.compile(rf"</{name}\s*[^>]*>", re.I) for name in RAW}

MAIN, MARKED, OPEN = 0, 1, 2


def _marked(name: str, attributes: str, in_main: bool) -> bool:
    if name in ASIDE or name == "header" and not in_main:
        return True
    if attributes and name not in ("html", "body", "article", "main") and ("class" in attributes or "id" in attributes or "role" in attributes or "CLASS" in attributes):
        for value in _NAMES.findall(attributes):
            if not ASIDE_WORDS.isdisjoint(re.split(r"[^a-z]+", value.lower())):
                return True
            if "header" in value.lower() and name in ("div", "section") and not in_main:
                return True
    return False


def blocks(page: str | None) -> list[tuple[str, int]]:
    """(text, kind) of the blocks of a page in page order; MAIN only where there is a main container."""
    page = page or ""
    container = "article" if re.search(r"<article[\s>]", page, re.I) else "main"
    out: list[tuple[str, int]] = []
    held: list[str] = []
    asides: list[list] = []  # [name, how many of that name are open]
    main = at = 0

    def close():
        if held:
            text = " ".join(entities.unescape("".join(held)).split())
            if text:
                out.append((text, MARKED if asides else MAIN if main else OPEN))
            held.clear()

    n = len(page)
    while at < n:
        m = _TAG.search(page, at)
        if m is None:
            held.append(page[at:])
            break
        if m.start() > at:
            held.append(page[at : m.start()])
        at = m.end()
        if m[0] == "<!--":
            end = page.find("-->", at)
            at = n if end < 0 else end + 3
            continue
        if m[2] is None:
            continue
        name, closing = m[2].lower(), bool(m[1])
        if name in RAW:
            if not closing and not m[3].endswith("/"):
                end = _CLOSE[name].search(page, at)
                at = n if end is None else end.end()
            if name not in INLINE:
                close()
            continue
        if name in INLINE:
            if name == "br":
                held.append(" ")
            elif not closing and m[3] and name not in VOID and not asides and _marked(name, m[3], main > 0):
                close()
                asides.append([name, 1])
            elif asides and asides[-1][0] == name and name not in VOID:
                asides[-1][1] += -1 if closing else 1
                if not asides[-1][1]:
                    close()
                    asides.pop()
            continue
        close()
        if name in VOID:
            continue
        if closing:
            if asides and asides[-1][0] == name:
                asides[-1][1] -= 1
                if not asides[-1][1]:
                    asides.pop()
            elif name == container and main:
                main -= 1
                if not main:
                    asides.clear()
        elif asides and asides[-1][0] == name:
            asides[-1][1] += 1
        elif not asides and _marked(name, m[3], main > 0):
            asides.append([name, 1])
        elif name == container and not asides:
            main += 1
    close()
    return out


PARSED = "key long, page_id long, url string, host string, has_open boolean, texts array<string>, kinds array<int>"


def parse(pages: DataFrame) -> DataFrame:
    """The blocks of every page, with a key that equal pages share."""
    url = F.col("url").cast("string")
    rest = F.when(F.instr(url, "://") > 0, F.substr(url, F.instr(url, "://") + 3)).otherwise(F.lit(""))
    given = pages.select(
        F.xxhash64(F.col("page_id"), F.col("html")).alias("key"), F.col("page_id").cast("long").alias("page_id"), url.alias("url"),
        F.coalesce(F.lower(F.regexp_extract(rest, "^[^/?#]*", 0)), F.lit("")).alias("host"), F.col("html").cast("string").alias("html"),
    )

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "html"):
                found = [blocks(x) for x in batch.column("html").to_pylist()]
                kinds = [[k for _, k in b] for b in found]
                yield pa.RecordBatch.from_arrays(
                    [*(batch.column(k) for k in ("key", "page_id", "url", "host")), pa.array([OPEN in k for k in kinds], pa.bool_()), pa.array([[t for t, _ in b] for b in found], pa.list_(pa.string())), pa.array(kinds, pa.list_(pa.int32()))],
                    names=["key", "page_id", "url", "host", "has_open", "texts", "kinds"],
                )

    return given.mapInArrow(look, PARSED)


def sorted_suffixes(tokens: np.ndarray, page: np.ndarray, run: int) -> tuple[np.ndarray, np.ndarray]:
    """(suffix array, rank of each place) by prefix doubling to ``run`` tokens; suffixes end with their page."""
    _, rank = np.unique(tokens, return_inverse=True)
    have, n = 1, len(tokens)
    while have < run:
        step = min(have, run - have)
        ahead = np.full(n, -1, np.int64)
        same = page[step:] == page[:-step]
        ahead[: n - step][same] = rank[step:][same]
        _, rank = np.unique(rank * np.int64(n + 2) + ahead + 1, return_inverse=True)
        have += step
    return np.argsort(rank, kind="stable"), rank


#: Bytes of text whose suffixes are sorted at once.
SORTED_BYTES = 4 << 20


def _some_pages(batch: pa.RecordBatch, most_bytes: int = SORTED_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts a batch between pages into ranges of about ``most_bytes`` of blocks; a longer page stands alone."""
    texts = batch.column("texts")
    upto = np.concatenate([[0], np.cumsum(pc.binary_length(texts.values).to_numpy(zero_copy_only=False), dtype=np.int64)])
    ends = upto[texts.offsets.to_numpy()]
    at = 0
    while at < batch.num_rows:
        stop = max(at + 1, int(np.searchsorted(ends, ends[at] + most_bytes, side="right")) - 1)
        yield batch.slice(at, stop - at)
        at = stop


def _streams(texts: list[list[str]], kinds: list[list[int]], whole: bool = False) -> tuple[np.ndarray, np.ndarray, list[list[tuple[int, int, int]]]]:
    """Token hashes, the stream of each, and for each page its (block, first, last) tokens outside its main text.

    Stream 2 i is what page i has outside its main text; with ``whole`` stream 2 i + 1 is its main text. Runs lie in one stream.
    """
    joined, spots = [], []
    for page, (ts, ks) in enumerate(zip(texts, kinds)):
        for main in (False, True)[: 1 + whole]:
            for k, (t, kind) in enumerate(zip(ts, ks)):
                if (kind == MAIN) == main:
                    joined.append(t)
                    spots.append((2 * page + main, k))
    data, offsets = K.raw(pa.array(joined, pa.large_string()))
    data = K.FOLDED[data]
    starts, ends, first = K.words(data, offsets, K.NOT_SPACE)
    tokens = K.span_hash(K.prefix_sums(data), starts, ends)
    stream = np.repeat(np.array([p for p, _ in spots], np.int64), np.diff(first))
    places: list[list[tuple[int, int, int]]] = [[] for _ in texts]
    for (p, k), a, b in zip(spots, first[:-1].tolist(), first[1:].tolist()):
        if not p % 2:
            places[p // 2].append((k, a, b))
    return tokens, stream, places


def _whole_runs(tokens: np.ndarray, page: np.ndarray, run: int) -> tuple[np.ndarray, np.ndarray]:
    """Places at which ``run`` tokens of one page start, and a hash of them."""
    h = K.window_hash(tokens, run)
    at = np.flatnonzero(page[: len(h)] == page[run - 1 :]) if len(h) else np.zeros(0, np.int64)
    return at, h[at]


def repeated_runs(parsed: DataFrame, run: int = RUN) -> DataFrame:
    """(host, h): runs of tokens that a host has on two or more different pages, main text included, as far as undeclared blocks may have them."""

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (some for whole in batches for some in _some_pages(whole)):
            hosts = batch.column("host").to_pylist()
            sig = batch.column("sig").to_numpy()
            tokens, stream, _ = _streams(batch.column("texts").to_pylist(), batch.column("kinds").to_pylist(), whole=True)
            if len(tokens) < run:
                continue
            names: dict[str, int] = {}
            host = np.array([names.setdefault(x, len(names)) for x in hosts])
            # one suffix array for each host, all at once: the host stands before its tokens' order
            order, rank = sorted_suffixes(tokens, stream, run)
            at, h = _whole_runs(tokens, stream, run)
            whole_run = np.zeros(len(tokens), bool)
            whole_run[at] = True
            hashed = np.zeros(len(tokens), np.uint64)
            hashed[at] = h
            page = stream // 2
            order = order[whole_run[order]]
            order = order[np.argsort(host[page[order]], kind="stable")]
            if not len(order):
                continue
            own, group = host[page[order]], rank[order]
            head = np.flatnonzero(np.concatenate([[True], (own[1:] != own[:-1]) | (group[1:] != group[:-1])]))
            s = sig[page[order]]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([hosts[i] for i in page[order[head]].tolist()], pa.string()), pa.array(hashed[order[head]].view(np.int64)), pa.array(np.minimum.reduceat(s, head)), pa.array(np.maximum.reduceat(s, head)),
                    pa.array(np.logical_or.reduceat(stream[order] % 2 == 0, head)),
                ],
                names=["host", "h", "lo", "hi", "outside"],
            )

    entries = parsed.select("host", "sig", "texts", "kinds").mapInArrow(look, "host string, h long, lo long, hi long, outside boolean")
    entries = Sieve(_asked(parsed, run), "h").may_have(entries, "h", F.col("outside"))
    met = entries.groupBy("host", "h").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    return met.where("lo <> hi").select("host", "h")


def _asked(parsed: DataFrame, run: int) -> DataFrame:
    """(key, host, h, at): the runs outside the main text of pages that have undeclared blocks."""

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            tokens, stream, _ = _streams(batch.column("texts").to_pylist(), batch.column("kinds").to_pylist())
            at, h = _whole_runs(tokens, stream, run)
            if not len(at):
                continue
            begin, page = np.searchsorted(stream, stream[at]), stream[at] // 2  # the stream's first token
            hosts, key = batch.column("host").to_pylist(), batch.column("key").to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(key[page]), pa.array([hosts[i] for i in page.tolist()], pa.string()), pa.array(h.view(np.int64)), pa.array((at - begin).astype(np.int32))], names=["key", "host", "h", "at"])

    return parsed.where("has_open").select("key", "host", "texts", "kinds").mapInArrow(look, "key long, host string, h long, at int")


def extract(pages: DataFrame, run: int = RUN) -> DataFrame:
    """page_id, url, text and n_chars of every page."""
    parsed = parse(pages).withColumn("sig", F.xxhash64("texts"))
    parsed = materialize(parsed, "blocks")
    # written, so that the suffix arrays are made whatever the blocks then ask of them
    repeated = materialize(repeated_runs(parsed, run), "repeated")
    found = _asked(parsed, run).join(repeated, ["host", "h"])
    covered = found.groupBy("key").agg(F.collect_set("at").alias("covered"))
    columns = ["page_id", "url", "has_open", "texts", "kinds", "covered"]
    # pages without undeclared blocks don't take part in the join, so their texts aren't shuffled
    declared = parsed.where(~F.col("has_open")).withColumn("covered", F.lit(None).cast("array<int>")).select(*columns)
    loose_pages = parsed.where("has_open").join(covered, "key", "left").select(*columns)

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, kinds = batch.column("texts").to_pylist(), batch.column("kinds").to_pylist()
            has_open, hits = batch.column("has_open").to_pylist(), batch.column("covered").to_pylist()
            loose = [k for k, m in enumerate(has_open) if m]
            kept = [[t for t, k in zip(ts, ks) if k == MAIN] for ts, ks in zip(texts, kinds)]
            if loose:
                _, stream, places = _streams([texts[k] for k in loose], [kinds[k] for k in loose])
                n = np.bincount(stream // 2, minlength=len(loose)) if len(stream) else np.zeros(len(loose), np.int64)
                first = np.cumsum(n) - n
                for i, k in enumerate(loose):
                    at = np.array(sorted(hits[k] or []), np.int64)
                    mark = K.covered(int(n[i]), at, np.full(len(at), run))
                    if MAIN in kinds[k] and n[i] < run:
                        continue
                    stay = {b for b, s, e in places[i] if kinds[k][b] == OPEN and 2 * int(mark[s - first[i] : e - first[i]].sum()) < max(1, e - s)}
                    kept[k] = [t for b, (t, kind) in enumerate(zip(texts[k], kinds[k])) if kind == MAIN or b in stay]
            out = ["\n\n".join(x) for x in kept]
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(out, pa.string()), pa.array([len(x) for x in out], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    told = "page_id long, url string, text string, n_chars long"
    return declared.mapInArrow(decide, told).union(loose_pages.mapInArrow(decide, told))


def query(spark, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
