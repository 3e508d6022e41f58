"""Suffix-array dedup: bytes covered by a repeated string of ``length`` bytes are removed.

A byte goes when some string of ``length`` bytes over it also starts anywhere else, in another
document or the same; matches never cross documents, and all is judged on the input.

1. Equal texts are one, told by 128 bits of their SHA-256. A text that occurs twice goes whole if it is long enough.
2. Of the suffixes of a text only those at *anchors* are kept: every window of ``length`` bytes
   appoints the start of its least-hashed ``gram`` (the first of ties), so equal windows appoint equal
   places and no repeat is lost. Anchors whose gram occurs nowhere else are dropped by a count.
3. Each other anchor brings its suffix (``length`` bytes from it on) and what stands before it.
   Equal such surroundings are counted as one before the shuffle. By gram they come to a task, which
   sorts the suffixes deep-shallow: a multikey quicksort orders them by their first 32 bytes, and a
   blind trie each group that is still equal. Reversed surroundings are sorted alike. From both
   arrays of common prefixes follows, exactly, how far to the left and right of an anchor there are
   windows that occur again.
4. A gram with too many different surroundings for one task goes by digests of its windows instead,
   counted with partial aggregates; the result is the same.

Defined results: null and empty texts have 0 bytes and lose none; a text shorter than ``length``
loses nothing; repeated rows are removed whole if they are long enough; an empty table gives no
rows; extra columns are ignored by ``spans`` and pass through ``apply``; very long texts are read
whole, in stretches that overlap by a window.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.llm import textkit as K
from edgesketch.llm.common import materialize, partitions_for, scratch_scope, table, text_slices

LENGTH = 400
#: Different surroundings of one gram that a task sorts.
MOST_SURROUNDINGS = 20_000
#: A gram with more anchors is frequent; at most so many frequent grams are broadcast, the rest is dealt like any.
HOT_ANCHORS, HOT_GRAMS = 2_000, 50_000
#: Bytes that the multikey quicksort orders by, at most.
SHALLOW = 32


def gram_of(length: int) -> int:
    return max(1, 2 * length // 5)


def anchors_of(data: np.ndarray, offsets: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, place in the text, gram hash) of the anchors of all texts, place by place."""
    gram = gram_of(length)
    width = length - gram + 1
    if len(data) < length:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    sums = K.prefix_sums(data)
    place = np.arange(len(data) - gram + 1)
    h = K.span_hash(sums, place, place + gram)
    low = np.uint64((1 << max(24, len(data).bit_length())) - 1)
    v = (h & ~low) | place.astype(np.uint64)
    n = len(v)
    padded = np.full(-(-n // width) * width, np.iinfo(np.uint64).max)
    padded[:n] = v
    blocks = padded.reshape(-1, width)
    head = np.minimum.accumulate(blocks, axis=1).reshape(-1)
    tail = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    least = np.minimum(tail[: n - width + 1], head[width - 1 : n])
    # windows that lie in one text
    starts = np.arange(len(least))
    text = np.searchsorted(offsets, starts, side="right") - 1
    inside = starts + length <= offsets[text + 1]
    chosen = (least[inside] & low).astype(np.int64)
    if len(chosen):
        chosen = chosen[np.concatenate([[True], chosen[1:] != chosen[:-1]])]
    text = np.searchsorted(offsets, chosen, side="right") - 1
    return text, chosen - offsets[text], h[chosen]


STRETCH = 1 << 20


def anchors_of_long(data: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Anchors of one very long text, stretch by stretch."""
    at, keys = [], []
    for start in range(0, max(1, len(data) - length + 1), STRETCH):
        part = data[start : start + STRETCH + length - 1]
        _, p, h = anchors_of(part, np.array([0, len(part)]), length)
        at.append(p + start)
        keys.append(h)
    at, keys = np.concatenate(at), np.concatenate(keys)
    at, first = np.unique(at, return_index=True)
    return at, keys[first]


def _tid(text):
    """128 bits of the SHA-256 of a text, which name it."""
    return F.unhex(F.substring(F.sha2(text, 256), 1, 32))


def _texts(docs: DataFrame) -> DataFrame:
    """doc_id, text, tid, and did: 60 bits for anchors only, where a text of equal bits adds places to look at and no verdict."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text")).withColumn("tid", _tid("text"))
    return df.withColumn("did", F.conv(F.substring(F.hex("tid"), 1, 15), 16, 10).cast("long"))


def anchor_rows(texts: DataFrame, length: int) -> DataFrame:
    """(key, did, at) of every anchor of the texts."""

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text", 1 << 20):
                data, offsets = K.raw(batch.column("text"))
                if batch.num_rows == 1 and len(data) > STRETCH:
                    at, key = anchors_of_long(data, length)
                    text = np.zeros(len(at), np.int64)
                else:
                    text, at, key = anchors_of(data, offsets, length)
                did = batch.column("did").to_numpy()[text]
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(did), pa.array(at.astype(np.int32))], names=["key", "did", "at"])

    return texts.select("did", "text").mapInArrow(look, "key long, did long, at int")


def common_prefix(a: bytes, b: bytes) -> int:
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    lo = 0
    while n - lo > 1:
        mid = (lo + n) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            n = mid
    return lo


class BlindTrie:
    """Orders strings that share long prefixes: inner nodes know only how deep they part and by which byte."""

    def __init__(self, strings: list[bytes]):
        self.strings = strings
        self.root = None  # a leaf is an int, an inner node is (depth, {byte or -1: child})
        for k in range(len(strings)):
            self._add(k)

    def _add(self, k: int) -> None:
        s = self.strings[k]
        if self.root is None:
            self.root = k
            return
        node = self.root
        while not isinstance(node, int):
            depth, kids = node
            child = kids.get(s[depth] if depth < len(s) else -1)
            node = next(iter(kids.values())) if child is None else child
        other = self.strings[node]
        deep = common_prefix(s, other)
        parent, letter, node = None, None, self.root
        while not isinstance(node, int) and node[0] < deep:
            parent, letter = node, s[node[0]]
            node = node[1][letter]
        mine = s[deep] if deep < len(s) else -1
        if not isinstance(node, int) and node[0] == deep:
            node[1][mine] = k
            return
        theirs = other[deep] if deep < len(other) else -1
        made = (deep, {theirs: node, mine: k})
        if parent is None:
            self.root = made
        else:
            parent[1][letter] = made

    def walk(self) -> tuple[list[int], list[int]]:
        """(order, common prefix of each with the one before it)."""
        order, lcp, stack = [], [], [(self.root, 0)]
        while stack:
            node, before = stack.pop()
            if isinstance(node, int):
                order.append(node)
                lcp.append(before)
                continue
            depth, kids = node
            letters = sorted(kids, reverse=True)
            stack += [(kids[c], depth) for c in letters[:-1]]
            stack.append((kids[letters[-1]], before))
        return order, lcp


def shallow_groups(suffixes: list[bytes], shallow: int) -> Iterator[list[int]]:
    """Multikey quicksort by the first ``shallow`` bytes, in words of 8: groups that are still equal, in order."""
    if not shallow:
        yield list(range(len(suffixes)))
        return
    words = np.frombuffer(b"".join(s[:shallow].ljust(shallow, b"\0") for s in suffixes), ">u8").astype(np.uint64).reshape(-1, shallow // 8)
    stack: list[tuple[np.ndarray, int]] = [(np.arange(len(suffixes)), 0)]
    while stack:
        index, depth = stack.pop()
        if len(index) == 1 or depth == words.shape[1]:
            yield index.tolist()
            continue
        if len(index) <= 24:
            by: dict[bytes, list[int]] = {}
            for i in index.tolist():
                by.setdefault(suffixes[i][:shallow], []).append(i)
            for s in sorted(by):
                yield by[s]
            continue
        w = words[index, depth]
        pivot = np.partition(w, len(w) // 2)[len(w) // 2]
        for part, deeper in ((w > pivot, 0), (w == pivot, 1), (w < pivot, 0)):
            if part.any():
                stack.append((index[part], depth + deeper))


def _sorted_distinct(strings: list[bytes]) -> tuple[np.ndarray, list[int], list[int]]:
    """(which distinct string each is, order of the distinct ones, common prefix of each with the one before)."""
    names: dict[bytes, int] = {}
    which = np.array([names.setdefault(x, len(names)) for x in strings])
    return which, *BlindTrie(list(names)).walk()


def _pairwise(order: list[int], lcp: list[int], strings: list[bytes], which: np.ndarray, most: int) -> np.ndarray:
    """Common prefix of every two strings of a small group, at most ``most``."""
    m = len(order)
    out = np.zeros((m, m), np.int64)
    lcp = np.minimum(np.array(lcp), most)
    for i in range(m - 1):
        run = np.minimum.accumulate(lcp[i + 1 :])
        out[order[i], order[i + 1 :]] = run
        out[order[i + 1 :], order[i]] = run
    for x, k in zip(strings, which.tolist()):
        out[k, k] = min(len(x), most)
    return out[np.ix_(which, which)]


def reaches(lefts: list[bytes], rights: list[bytes], length: int) -> list[tuple[int, int] | None]:
    """How far left and right of each anchor windows lie that another of the group has, or None.

    ``lefts`` are reversed: what stands before an anchor, from it on to the left.
    """
    m, most = len(rights), length - gram_of(length)
    right, ro, rl = _sorted_distinct(rights)
    before, lo, ll = _sorted_distinct(lefts)
    if m <= 64:
        r = _pairwise(ro, rl, rights, right, length)
        left = _pairwise(lo, ll, lefts, before, most)
        good = (left + r >= length) & ~np.eye(m, dtype=bool)
        a, b = np.where(good, left, -1).max(axis=1), np.where(good, r, -1).max(axis=1)
        return [(int(x), int(y)) if x >= 0 else None for x, y in zip(a, b)]
    rank_r, rank_l = np.empty(len(ro), np.int64), np.empty(len(lo), np.int64)
    rank_r[ro], rank_l[lo] = np.arange(len(ro)), np.arange(len(lo))
    rl, ll = np.array(rl), np.array(ll)
    size_r, size_l = np.array([len(x) for x in rights]), np.array([len(x) for x in lefts])
    far, near = np.full(m, -1), np.full(m, -1)
    for k in range(most + 1):
        fit = np.flatnonzero((size_l >= k) & (size_r >= length - k))
        if len(fit) < 2:
            continue
        cl, cr = np.cumsum(ll < k), np.cumsum(rl < length - k)
        code = cl[rank_l[before[fit]]] * (m + 1) + cr[rank_r[right[fit]]]
        _, back, n = np.unique(code, return_inverse=True, return_counts=True)
        again = fit[n[back] > 1]
        far[again] = k
        near[again[near[again] < 0]] = length - k
    return [(int(x), int(y)) if x >= 0 else None for x, y in zip(far, near)]


def _sort_task(length: int):
    """Over surroundings sorted by key: (key, cx, cy, left, right) of those with windows that occur again."""

    shallow = min(SHALLOW, gram_of(length)) // 8 * 8  # not deeper than what a group surely shares

    def look(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def told(block: list[tuple]):
            # surroundings that occur twice are windows that occur again, all over
            out = [(key, cx, cy, len(left), len(right)) for key, cx, cy, n, left, right in block if n > 1]
            suffixes = [b[5] for b in block]
            for group in shallow_groups(suffixes, shallow):
                if len(group) < 2:
                    continue
                for i, reach in zip(group, reaches([block[i][4][::-1] for i in group], [suffixes[i] for i in group], length)):
                    if reach is not None and block[i][3] == 1:
                        out.append((*block[i][:3], *reach))
            if out:
                return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32()))], names=["key", "cx", "cy", "l", "r"])
            return None

        for batch in rows:
            held += zip(*(batch.column(k).to_pylist() for k in ("key", "cx", "cy", "n", "before", "after")))
            if len(held) > 20_000:
                last = held[-1][0]
                cut = next((i for i in range(len(held) - 1, -1, -1) if held[i][0] != last), -1) + 1
                if cut:
                    if (out := told(held[:cut])) is not None:
                        yield out
                    held = held[cut:]
        if held and (out := told(held)) is not None:
            yield out

    return look


def _by_digest(rows: DataFrame, length: int) -> DataFrame:
    """The same verdicts for grams with too many surroundings, from digests of the single windows."""
    most = length - gram_of(length)
    left = F.explode(F.sequence(F.greatest(F.lit(0), F.lit(length) - F.octet_length("after")), F.least(F.octet_length("before"), F.lit(most))))
    fits = F.octet_length("before") + F.octet_length("after") >= length
    one = rows.where(fits).select("key", "cx", "cy", "n", "before", "after", left.alias("left"))
    whole = F.concat("before", "after")
    window = F.substr(whole, F.octet_length("before") - F.col("left") + 1, F.lit(length))
    one = one.select("key", "cx", "cy", "n", "left", F.md5(window).alias("w"))
    again = one.groupBy("key", "left", "w").agg(F.sum("n").alias("m")).where("m > 1").drop("m")
    met = one.join(again, ["key", "left", "w"]).groupBy("key", "cx", "cy").agg(F.max("left").cast("int").alias("l"), (F.lit(length) - F.min("left")).cast("int").alias("r"))
    return met.select("key", "cx", "cy", "l", "r")


HITS = "tid binary, text string, at array<int>, key array<long>, cx array<long>, cy array<long>"


def _named_hits(length: int):
    """Texts with their anchors in order, and of each two hashes that name what surrounds it."""
    before = length - gram_of(length)

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text", 1 << 20):
                data, offsets = K.raw(batch.column("text"))
                own = batch.column("places")
                own = own.combine_chunks() if isinstance(own, pa.ChunkedArray) else own
                n = np.diff(own.offsets.to_numpy())
                at, key = (own.flatten().field(k).to_numpy().astype(np.int64) for k in ("at", "key"))
                text = np.repeat(np.arange(len(n)), n)
                size = np.diff(offsets)[text]
                good = at < size  # a place of another text whose 60 bits are equal may lie outside
                text, at, key, size = text[good], at[good], key[good], size[good]
                a, b = offsets[text] + np.maximum(0, at - before), offsets[text] + np.minimum(size, at + length)
                side = np.minimum(at, before).astype(np.uint64)
                names = [K.mix(K.span_hash(K.prefix_sums(data, codes), a, b) + side).view(np.int64) for codes in (K.BYTE_CODE, K.SECOND_CODE)]
                edge = np.searchsorted(text, np.arange(len(n) + 1)).astype(np.int32)
                lists = [pa.ListArray.from_arrays(pa.array(edge), pa.array(x)) for x in (at.astype(np.int32), key, *names)]
                yield pa.RecordBatch.from_arrays([batch.column("tid"), batch.column("text"), *lists], names=["tid", "text", "at", "key", "cx", "cy"])

    return look


def _surroundings(length: int):
    """(key, cx, cy, before, after) of every anchor: slices of the texts, cut by their offsets."""
    before = length - gram_of(length)

    def cells(data: np.ndarray, a: np.ndarray, b: np.ndarray) -> pa.Array:
        n = b - a
        ends = np.cumsum(n)
        index = np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(a - (ends - n), n)
        return pa.BinaryArray.from_buffers(pa.binary(), len(a), [None, pa.py_buffer(np.append(0, ends).astype(np.int32)), pa.py_buffer(data[index])])

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text", 1 << 20):
                data, offsets = K.raw(batch.column("text"))
                n = np.diff(batch.column("at").offsets.to_numpy())
                at, key, cx, cy = (batch.column(k).flatten().to_numpy() for k in ("at", "key", "cx", "cy"))
                text = np.repeat(np.arange(len(n)), n)
                p = offsets[text] + at
                a, b = np.maximum(offsets[text], p - before), np.minimum(offsets[text + 1], p + length)
                for i in range(0, len(p), 10_000):
                    some = slice(i, i + 10_000)
                    yield pa.RecordBatch.from_arrays([pa.array(key[some]), pa.array(cx[some]), pa.array(cy[some]), cells(data, a[some], p[some]), cells(data, p[some], b[some])], names=["key", "cx", "cy", "before", "after"])

    return look


def _spans_of(docs_texts: DataFrame, length: int, most_surroundings: int) -> tuple[DataFrame, DataFrame]:
    """(texts that have repeated grams, (tid, spans) of those with something to remove)."""
    spark = docs_texts.sparkSession
    named = docs_texts.where(F.octet_length("text") >= length)
    anchors = materialize(anchor_rows(named, length).distinct(), "anchors")  # equal texts bring equal rows
    again = materialize(anchors.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "grams")
    # the most frequent grams, a bounded number, meet their anchors where these lie; only the rest is dealt by gram
    hot = F.broadcast(again.where(F.col("n") > HOT_ANCHORS).orderBy(F.desc("n"), "key").limit(HOT_GRAMS).select("key"))
    cold = anchors.join(hot, "key", "left_anti").join(again.select("key"), "key")
    places = anchors.join(hot, "key").union(cold).groupBy("did").agg(F.collect_list(F.struct("at", "key")).alias("places"))
    # one row for each text: equal texts meet as one after the filter by places
    met = named.select("tid", "did", "text").join(places, "did").groupBy("tid").agg(F.first("text").alias("text"), F.first("places").alias("places"))
    hits = materialize(met.mapInArrow(_named_hits(length), HITS), "hits")
    around = hits.select("text", "at", "key", "cx", "cy").mapInArrow(_surroundings(length), "key long, cx long, cy long, before binary, after binary")
    distinct = materialize(around.groupBy("key", "cx", "cy").agg(F.count(F.lit(1)).alias("n"), F.first("before").alias("before"), F.first("after").alias("after")), "surroundings")
    large = distinct.groupBy("key").agg(F.count(F.lit(1)).alias("k")).where(F.col("k") > most_surroundings).select("key")
    large = materialize(large, "large-grams")
    if large.isEmpty():
        small, verdicts = distinct, None
    else:
        small = distinct.join(large, "key", "left_anti")
        verdicts = _by_digest(distinct.join(large, "key", "left_semi"), length)
    dealt = small.repartition(partitions_for(spark), "key").sortWithinPartitions("key")
    sorted_ones = dealt.mapInArrow(_sort_task(length), "key long, cx long, cy long, l int, r int")
    verdicts = sorted_ones if verdicts is None else sorted_ones.union(verdicts)
    places = hits.select("tid", F.explode(F.arrays_zip("at", "key", "cx", "cy")).alias("x")).select("tid", "x.*")
    found = places.join(verdicts, ["key", "cx", "cy"])
    spans = found.groupBy("tid").agg(F.collect_list(F.struct((F.col("at") - F.col("l")).alias("a"), (F.col("at") + F.col("r")).alias("b"))).alias("spans"))
    return hits, spans


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Maximal runs of overlapping or touching spans."""
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def cut(body: bytes, runs: list[tuple[int, int]]) -> bytes:
    out, at = [], 0
    for a, b in runs:
        out.append(body[at:a])
        at = b
    return b"".join([*out, body[at:]])


CUTS = "tid binary, n_removed long, n_spans long, kept_sha256 string, kept_text string, runs array<struct<a:int,b:int>>"


def cuts(texts: DataFrame, length: int = LENGTH, most_surroundings: int = MOST_SURROUNDINGS, with_text: bool = False) -> DataFrame:
    """For each text with something to remove: what goes, and the rest as a digest, and as text if asked for.

    A character of which bytes go is not in the text; the digest is of the bytes that are left.
    """
    spark = texts.sparkSession

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for tid, text, own in zip(*(batch.column(k).to_pylist() for k in ("tid", "text", "spans"))):
                body, runs = text.encode(), merged([(s["a"], s["b"]) for s in own])
                left = cut(body, runs)
                out.append((tid, len(body) - len(left), len(runs), hashlib.sha256(left).hexdigest(), left.decode(errors="ignore") if with_text else None, [{"a": a, "b": b} for a, b in runs]))
            if out:
                kinds = (pa.binary(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(pa.struct([("a", pa.int32()), ("b", pa.int32())])))
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), kinds)], names=["tid", "n_removed", "n_spans", "kept_sha256", "kept_text", "runs"])

    with scratch_scope(spark):
        hits, spans = _spans_of(texts, length, most_surroundings)
        return materialize(hits.select("tid", "text").join(spans, "tid").mapInArrow(look, CUTS), "cuts", outer=True)


_EMPTY = hashlib.sha256(b"").hexdigest()


def spans(docs: DataFrame, length: int = LENGTH, most_surroundings: int = MOST_SURROUNDINGS) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and kept_sha256 of every document, its removed runs, and the text that is left.

    A character of which bytes go is not in the text; the digest is of all bytes that are left.
    """
    texts = _texts(docs)
    twice = texts.groupBy("tid").agg(F.count(F.lit(1)).alias("copies")).where("copies > 1")
    found = texts.drop("did").join(twice, "tid", "left").join(cuts(texts, length, most_surroundings, with_text=True), "tid", "left")
    found = found.withColumn("n_bytes", F.octet_length("text").cast("long"))
    gone = (F.col("copies") > 1) & (F.col("n_bytes") >= length)
    all_of_it = F.array(F.struct(F.lit(0).alias("a"), F.col("n_bytes").cast("int").alias("b")))
    return found.select(
        "doc_id", "n_bytes",
        F.when(gone, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0).cast("long"))).alias("n_removed"),
        F.when(gone, F.lit(1).cast("long")).otherwise(F.coalesce("n_spans", F.lit(0).cast("long"))).alias("n_spans"),
        F.when(gone, F.lit(_EMPTY)).otherwise(F.coalesce("kept_sha256", F.sha2("text", 256))).alias("kept_sha256"),
        F.when(gone, all_of_it).otherwise(F.col("runs")).alias("runs"),
        F.when(gone, F.lit("")).otherwise(F.coalesce("kept_text", "text")).alias("text"),
    )


def apply(docs: DataFrame, length: int = LENGTH, most_surroundings: int = MOST_SURROUNDINGS) -> DataFrame:
    """The documents with the repeated bytes removed from their texts; all columns stay.

    A document that had a text and loses all of it is dropped.
    """
    texts = _texts(docs)
    own = docs.withColumn("__es_tid", _tid(F.coalesce(F.col("text").cast("string"), F.lit(""))))
    twice = texts.groupBy(F.col("tid").alias("__es_twice")).agg(F.count(F.lit(1)).alias("__es_copies")).where("__es_copies > 1")
    found = own.join(twice, F.col("__es_tid") == F.col("__es_twice"), "left")
    cuts_ = cuts(texts, length, most_surroundings, with_text=True).select(F.col("tid").alias("__es_t"), F.col("kept_text").alias("__es_kept"))
    found = found.join(cuts_, F.col("__es_tid") == F.col("__es_t"), "left")
    gone = (F.col("__es_copies") > 1) & (F.octet_length("text") >= length)
    text = F.when(gone, F.lit("")).otherwise(F.coalesce("__es_kept", "text"))
    changed = gone | F.col("__es_kept").isNotNull()
    out = found.withColumn("__es_new", text).where(~F.coalesce(changed & (F.length("__es_new") == 0), F.lit(False)))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.coalesce(changed, F.lit(False)), F.length("__es_new").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.withColumn("text", F.col("__es_new")).select(*docs.columns)


def query(spark, sf_dir: str) -> DataFrame:
    return spans(table(spark, sf_dir, "documents")).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "text")
