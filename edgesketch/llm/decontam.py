"""Benchmark decontamination: a broadcast hash set of normalised test n-grams.

Words are ``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`` of the text with A-Z lower-cased. A window is
``width`` consecutive words of an item; an item of fewer words, but not none, is one window. The
windows of the items are hashed and broadcast in blocks of a fixed byte size, one pass over the
documents for each block; every token window of every document is looked up in the set (NumPy over
the whole Arrow batch), each hit is verified against the item's words, and the verified spans mark
the words to remove.

Defined results: a null or empty text has no words and no hits; an item without words has no
window; repeated item ids count once; repeated document rows give one row each; an empty table gives
no rows; extra columns pass through ``decontaminate`` and are ignored by ``scan``. Very long texts
are scanned whole, alone in their slice.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StringType, StructType

from edgesketch.llm import textkit as K
from edgesketch.llm.common import materialize, table, text_slices

WIDTH = 10
#: Bytes of item text in one broadcast block; a larger benchmark takes more blocks, one pass each.
BLOCK_BYTES = 8 << 20


class WindowSet:
    """The windows of a block of items by rising hash, with where their words lie in one body of words."""

    def __init__(self, items: list[tuple[object, str | None]], width: int = WIDTH):
        data, offsets = K.raw(pa.array([t or "" for _, t in items], pa.large_string()))
        starts, ends, first = K.words(data, offsets, K.ALNUM)
        folded = K.FOLDED[data]
        hashes = K.span_hash(K.prefix_sums(folded), starts, ends)
        self.ids = [str(item) for item, _ in items]
        self.body = b" ".join(folded[s:e].tobytes() for s, e in zip(starts.tolist(), ends.tolist()))
        to = np.cumsum(ends - starts + 1) - 1
        counts = np.diff(first)
        #: for each length of window: hashes, first byte, byte after the last, and number of the item
        self.sets: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = {}
        # a 2**20-bit first test of the top bits keeps the sorted look-up for the few that pass it
        self.gate: dict[int, np.ndarray] = {}
        for n in np.unique(np.minimum(counts[counts > 0], width)).tolist():
            if n < width:
                item = np.flatnonzero(counts == n)
                at = first[item]
            else:
                at = np.arange(max(0, len(starts) - n + 1))
                item = K.owner(first, at)
                whole = at + n <= first[item + 1]
                at, item = at[whole], item[whole]
            h = K.window_hash(hashes, n)[at]
            order = np.argsort(h, kind="stable")
            at, item = at[order], item[order]
            self.sets[n] = h[order], to[at] - (ends - starts)[at], to[at + n - 1], item
            self.gate[n] = np.zeros(1 << 20, bool)
            self.gate[n][(h >> np.uint64(44)).astype(np.int64)] = True

    def find(self, column) -> tuple[np.ndarray, np.ndarray, np.ndarray, list, list[set[str]], np.ndarray]:
        """(first word of each text, hit starts, hit lengths, spans of words, items of each text, first bytes)."""
        data, offsets = K.raw(column)
        starts, ends, first = K.words(data, offsets, K.ALNUM)
        folded = K.FOLDED[data]
        hashes = K.span_hash(K.prefix_sums(folded), starts, ends)
        found_at, found_len = [], []
        items: list[set[str]] = [set() for _ in range(len(offsets) - 1)]
        for n, (known, low, high, item) in self.sets.items():
            h = K.window_hash(hashes, n)
            maybe = np.flatnonzero(self.gate[n][(h >> np.uint64(44)).astype(np.int64)])
            if not len(maybe):
                continue
            lo, hi = np.searchsorted(known, h[maybe]), np.searchsorted(known, h[maybe], side="right")
            maybe, lo, hi = maybe[lo < hi], lo[lo < hi], hi[lo < hi]
            text = K.owner(first, maybe)
            keep = maybe + n <= first[text + 1]
            for i, k, a, b in zip(maybe[keep].tolist(), text[keep].tolist(), lo[keep].tolist(), hi[keep].tolist()):
                words = b" ".join(folded[s:e].tobytes() for s, e in zip(starts[i : i + n].tolist(), ends[i : i + n].tolist()))
                got = [self.ids[item[j]] for j in range(a, b) if self.body[low[j] : high[j]] == words]
                if got:
                    found_at.append(i)
                    found_len.append(n)
                    items[k].update(got)
        return first, np.array(found_at, np.int64), np.array(found_len, np.int64), [starts, ends], items, offsets


def window_blocks(benchmark: DataFrame, width: int = WIDTH, block_bytes: int = BLOCK_BYTES) -> Iterator[Broadcast]:
    """Broadcast window sets, each of about ``block_bytes`` of item text, made one at a time."""
    spark = benchmark.sparkSession
    size = benchmark.select(F.sum(F.octet_length("text")).alias("b")).first().b or 0
    blocks = max(1, -(-size // block_bytes))
    for k in range(blocks):
        part = benchmark.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k).select("item_id", "text")
        yield spark.sparkContext.broadcast(WindowSet([(r.item_id, r.text) for r in part.toLocalIterator()], width))


#: What earlier passes found: runs of hit words of a text, and the items.
RUNS, ITEMS = "__es_runs", "__es_items"
_SPANS = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64())]))


class Marks:
    """The hit words and items of a slice of texts, of this block and of those before."""

    def __init__(self, batch: pa.RecordBatch, block: WindowSet):
        first, at, length, (self.starts, self.ends), self.items, self.offsets = block.find(batch.column("text"))
        hit = K.covered(int(first[-1]), at, length)
        if RUNS in batch.schema.names:
            for k, (runs, items) in enumerate(zip(batch.column(RUNS).to_pylist(), batch.column(ITEMS).to_pylist())):
                self.items[k].update(items)
                for run in runs:
                    hit[first[k] + run["first"] : first[k] + run["last"]] = True
        total = np.concatenate([[0], np.cumsum(hit)])
        self.first, self.n_words, self.n_hit = first, np.diff(first), total[first[1:]] - total[first[:-1]]
        #: (first word, word after the last) of each run, counted within its text
        self.runs: list[list[tuple[int, int]]] = [[] for _ in self.items]
        for k in np.flatnonzero(self.n_hit).tolist():
            edge = np.diff(np.concatenate([[0], hit[first[k] : first[k + 1]].astype(np.int8), [0]]))
            self.runs[k] = list(zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist()))

    def spans(self, k: int) -> list[tuple[int, int]]:
        """Byte ranges of the runs of text ``k``."""
        f, o = self.first[k], self.offsets[k]
        return [(int(self.starts[f + a] - o), int(self.ends[f + b - 1] - o)) for a, b in self.runs[k]]


def _pairs(runs: list[list[tuple[int, int]]]) -> pa.Array:
    return pa.array([[{"first": a, "last": b} for a, b in x] for x in runs], _SPANS)


def _earlier_passes(docs: DataFrame, benchmark: DataFrame, width: int, block_bytes: int) -> tuple[DataFrame, Broadcast]:
    """The documents with what all blocks but the last find in them, and the last block.

    Each of these passes is written before the next, so that no task holds two blocks.
    """
    blocks = window_blocks(benchmark, width, block_bytes)
    block = next(blocks)
    for k, following in enumerate(blocks):
        schema = StructType([f for f in docs.schema if f.name not in (RUNS, ITEMS)])
        schema = schema.add(RUNS, ArrayType(StructType().add("first", LongType()).add("last", LongType()))).add(ITEMS, ArrayType(StringType()))

        def mark(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                for batch in text_slices(whole, "text"):
                    marks = Marks(batch, block.value)
                    cols = [(n, c) for n, c in zip(batch.schema.names, batch.columns) if n not in (RUNS, ITEMS)]
                    cols += [(RUNS, _pairs(marks.runs)), (ITEMS, pa.array([sorted(x) for x in marks.items], pa.list_(pa.string())))]
                    yield pa.RecordBatch.from_arrays([c for _, c in cols], names=[n for n, _ in cols])

        docs = materialize(docs.mapInArrow(mark, schema), f"marks-{k}")
        block.unpersist()
        block = following
    return docs, block


SCAN = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, spans array<struct<first:long,last:long>>"


def scan(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per document: word counts, the items found, and byte spans of the hit runs."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    docs, block = _earlier_passes(docs, benchmark, width, block_bytes)

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text"):
                marks = Marks(batch, block.value)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id"),
                        pa.array(marks.n_words, pa.int64()),
                        pa.array(marks.n_hit, pa.int64()),
                        pa.array([len(x) for x in marks.items], pa.int64()),
                        pa.array([hashlib.sha256(",".join(sorted(x)).encode()).hexdigest() for x in marks.items], pa.string()),
                        pa.array(marks.n_hit > 0, pa.bool_()),
                        _pairs([marks.spans(k) for k in range(len(marks.items))]),
                    ],
                    names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "spans"],
                )

    return docs.mapInArrow(look, SCAN)


def cut_spans(text: str | None, spans: list[tuple[int, int]]) -> str | None:
    """The text without the given byte ranges."""
    if text is None or not spans:
        return text
    body, out, at = text.encode(), [], 0
    for first, last in sorted(spans):
        out.append(body[at:first])
        at = max(at, last)
    out.append(body[at:])
    return b"".join(out).decode()


def decontaminate(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, whole_above: float = 0.5, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Removes the hit spans; a document goes whole when more than ``whole_above`` of its words are hit.

    All columns of ``docs`` stay, ``text`` is cut; a column ``n_chars`` is set anew if there is one.
    """
    schema, has_chars = docs.schema, "n_chars" in docs.columns
    docs, block = _earlier_passes(docs, benchmark, width, block_bytes)

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text"):
                marks = Marks(batch, block.value)
                batch = batch.select([f.name for f in schema])
                if not marks.n_hit.any():
                    yield batch
                    continue
                texts, spot = batch.column("text").to_pylist(), batch.schema.get_field_index("text")
                for k in np.flatnonzero(marks.n_hit).tolist():
                    texts[k] = cut_spans(texts[k], marks.spans(k))
                cols = list(batch.columns)
                cols[spot] = pa.array(texts, batch.schema.field(spot).type)
                if has_chars:
                    c = batch.schema.get_field_index("n_chars")
                    old = cols[c].to_pylist()
                    cols[c] = pa.array([len(t) if h and t is not None else o for t, h, o in zip(texts, marks.n_hit.tolist(), old)], batch.schema.field(c).type)
                keep = marks.n_hit <= whole_above * marks.n_words
                yield pa.RecordBatch.from_arrays(cols, schema=batch.schema).filter(pa.array(keep))

    return docs.mapInArrow(clean, schema)


def query(spark, sf_dir: str) -> DataFrame:
    found = scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


_PATTERN = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
ORACLE = rf"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_PATTERN}') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_PATTERN}') AS w FROM benchmark),
bi AS (SELECT item_id, w, least(len(w), 10) AS n, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS i FROM b WHERE len(w) > 0),
bw AS (SELECT DISTINCT item_id, n, array_to_string(w[i:i + n - 1], ' ') AS g FROM bi),
sizes AS (SELECT DISTINCT n FROM bw),
di AS (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, sizes WHERE len(w) >= n),
hit AS (SELECT di.doc_id, di.i, di.n, bw.item_id FROM di JOIN bw ON di.n = bw.n AND array_to_string(di.w[di.i:di.i + di.n - 1], ' ') = bw.g),
places AS (SELECT doc_id, unnest(range(i, i + n)) AS p FROM (SELECT DISTINCT doc_id, i, n FROM hit)),
n_hit AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM places GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS s FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS s FROM hit) GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN n_hit USING (doc_id) LEFT JOIN its USING (doc_id)
"""
