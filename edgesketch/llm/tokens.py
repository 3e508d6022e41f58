"""Token counts by the whole-token shortcut, and the pre-token table that token-id output shares.

A byte-level vocabulary file splits a text at its special strings, then into pre-tokens by one
pattern; merges never cross a pre-token. Offline, each vocabulary string is encoded alone by the
library: those that come back as one token are *proven* whole tokens. Counting then splits whole
batches of texts into pre-tokens (NumPy over code points and their classes); a proven one counts 1,
any other is merged once by the library's own model and kept in a bounded hash table. A text with a
special string, or with a character that the splitting pattern and the library class differently
(found offline, code point by code point), is encoded whole by the library.

Defined results: null is the empty text, with 0 tokens; special strings in a text are one token each,
as is the library's default; very long texts are counted whole; repeated rows give a row each; extra
columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import functools
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.llm import textkit as K
from edgesketch.llm.common import table, text_slices

VOCABULARY = "byte_bpe_50k.json"
LIMIT = 1024
#: Pre-tokens that a worker remembers; when the table is full it starts again from the proven ones.
REMEMBERED = 1_000_000
#: Code points below it are compared one by one.
HIGHEST = 0x20000


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


LETTER, NUMBER, OTHER, SPACE, STRANGE = range(5)


class PreTokens:
    """The library's tokenizer, the classes of code points, and the whole tokens."""

    def __init__(self, path: str, proof: tuple | None = None):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_padding()
        self.library.no_truncation()
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.classes, self.whole = proof or (self._classes(), None)
        if proof is None:
            self.whole = self._whole()
        self.letters = str.maketrans({chr(b): c for b, c in _byte_letters().items()})

    def _classes(self) -> np.ndarray:
        """A class for each code point; STRANGE where the library splits unlike the pattern, or from HIGHEST on."""
        import public_tokenizers
        import regex

        pattern, split = regex.compile(public_tokenizers.PATTERN), self.library.pre_tokenizer.pre_tokenize_str
        out = np.full(0x110000, STRANGE, np.uint8)
        points = [c for c in range(HIGHEST) if not 0xD800 <= c < 0xE000]
        for kind, rule in ((LETTER, r"\p{L}"), (NUMBER, r"\p{N}"), (SPACE, r"\s"), (OTHER, r"[^\s\p{L}\p{N}]")):
            out[[ord(x) for x in regex.findall(rule, "".join(map(chr, points)))]] = kind
        for probe in ("a{}a", " {} 1"):
            width = len(probe) - 1
            for at in range(0, len(points), 50_000):
                part = points[at : at + 50_000]
                text = "".join(probe.format(chr(c)) + "\x01" for c in part)
                ours = {m.start() for m in pattern.finditer(text)}
                out[[part[i // (width + 1)] for i in ours ^ {a for _, (a, _) in split(text)}]] = STRANGE
        out[39] = OTHER  # the apostrophe's contractions are handled by split()
        return out

    def _whole(self) -> dict[str, int]:
        """Vocabulary strings that are one pre-token and encode alone as one token, with its id."""
        texts = [self.library.decode([i], skip_special_tokens=False) for i in range(self.library.get_vocab_size())]
        texts = sorted(t for t in set(texts) if t and "\ufffd" not in t and t not in self.special)
        coded = self.library.encode_batch_fast(texts, add_special_tokens=False)
        cps, offsets = code_points(texts)
        first = np.searchsorted(self.split(cps, offsets), offsets)
        return {t: e.ids[0] for t, e, n in zip(texts, coded, np.diff(first)) if len(e.ids) == 1 and n == 1}

    def split(self, cps: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Starts of the pre-tokens of all texts at once; they tile the texts."""
        n = len(cps)
        if not n:
            return np.zeros(0, np.int64)
        kind = self.classes[cps]
        edge = np.empty(n, bool)
        edge[0] = True
        np.not_equal(kind[1:], kind[:-1], out=edge[1:])
        heads = offsets[:-1][offsets[:-1] < n]
        edge[heads] = True
        begin = np.flatnonzero(edge)
        end = np.append(begin[1:], n)
        head = np.zeros(n + 1, bool)
        head[heads] = True
        head[n] = True
        what, follows = kind[begin], ~head[end]  # follows: the next run is of the same text
        space, lone = what == SPACE, end - begin == 1
        plain_end = cps[end - 1] == 32
        start = np.zeros(n + 1, bool)
        # a run that is no space takes one blank before it
        before = np.zeros(len(begin), bool)
        before[1:] = space[:-1] & follows[:-1] & plain_end[:-1]
        solid = ~space
        start[begin[solid] - before[solid]] = True
        start[begin[space & (~lone | ~plain_end | ~follows)]] = True
        start[end[space & follows & ~plain_end] - 1] = True
        # contractions: a lone apostrophe that takes one or two letters of the run after it
        mark = np.flatnonzero((what == OTHER) & lone & ~before & follows & (cps[begin] == 39))
        mark = mark[what[mark + 1] == LETTER] if len(mark) else mark
        if len(mark):
            at, room = end[mark], end[mark + 1] - begin[mark + 1]
            a, b = cps[at], cps[np.minimum(at + 1, n - 1)]
            one = np.isin(a, [ord(x) for x in "stmd"])
            two = (room > 1) & (((a == ord("r")) & (b == ord("e"))) | ((a == ord("v")) & (b == ord("e"))) | ((a == ord("l")) & (b == ord("l"))))
            takes = one.astype(np.int64) + 2 * two
            some = takes > 0
            start[at[some]] = False
            rest = some & (takes < room)
            start[at[rest] + takes[rest]] = True
        return np.flatnonzero(start[:n])

    def merge(self, piece: str) -> list[int]:
        """The ids of one pre-token, by the library's model."""
        return [t.id for t in self.library.model.tokenize(piece.encode().decode("latin-1").translate(self.letters))]


def _byte_letters() -> dict[int, str]:
    """The letters that byte-level vocabularies write for bytes: printable ones stand for themselves, the rest from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(rest)}


def code_points(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    offsets = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) for t in texts], out=offsets[1:])
    return np.frombuffer("".join(texts).encode("utf-32-le"), "<u4"), offsets


@functools.cache
def shared(path: str) -> PreTokens:
    return PreTokens(path)


class Coder:
    """Encodes or counts texts through a bounded hash table of pre-tokens, each merged once."""

    SLOTS = 1 << 22

    def __init__(self, pre: PreTokens, remembered: int = REMEMBERED):
        self.pre, self.remembered = pre, remembered
        self._reset()

    def _reset(self) -> None:
        self.keys = np.zeros(self.SLOTS, np.uint64)
        self.entry = np.zeros(self.SLOTS, np.int32)
        self.n = 0
        self.count = np.zeros(1024, np.int32)
        self.at = np.zeros(1024, np.int64)
        self.sign = np.zeros(1024, np.uint64)
        self.ids = np.zeros(4096, "<u4")
        self.filled = 0
        texts = list(self.pre.whole)
        cps, offsets = code_points(texts)
        h, sign = self._hashes(cps, offsets[:-1], offsets[1:])
        self._insert(h, sign, [[self.pre.whole[t]] for t in texts])

    @staticmethod
    def _hashes(cps, starts, ends):
        """A hash of each piece, and a check of length, first and last character beside it."""
        sums = np.zeros(len(cps) + 1, np.uint64)
        up, down = K.powers(len(cps) + 1)
        np.cumsum((cps.astype(np.uint64) + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93) * up[: len(cps)], out=sums[1:])
        long = (ends - starts).astype(np.uint64)
        h = K.mix((sums[ends] - sums[starts]) * down[starts] + long) | np.uint64(1)
        return h, (long << np.uint64(42)) ^ (cps[starts].astype(np.uint64) << np.uint64(21)) ^ cps[ends - 1].astype(np.uint64)

    def _slot(self, h: np.ndarray) -> np.ndarray:
        """The slot that has the hash, or -1."""
        at = (h >> np.uint64(42)).astype(np.int64)
        out = np.full(len(h), -1, np.int64)
        todo = np.arange(len(h))
        while len(todo):
            key = self.keys[at[todo]]
            got = key == h[todo]
            out[todo[got]] = at[todo[got]]
            todo = todo[~got & (key != 0)]
            at[todo] = (at[todo] + 1) & (self.SLOTS - 1)
        return out

    def _insert(self, h: np.ndarray, sign: np.ndarray, ids: list[list[int]]) -> None:
        """Adds distinct new hashes with their ids."""
        m = len(h)
        lengths = np.fromiter(map(len, ids), np.int64, m)
        total = int(lengths.sum())
        while self.n + m > len(self.count):
            self.count, self.at, self.sign = (np.concatenate([x, np.zeros_like(x)]) for x in (self.count, self.at, self.sign))
        while self.filled + total > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        new = np.arange(self.n, self.n + m)
        self.count[new], self.sign[new] = lengths, sign
        self.at[new] = self.filled + np.cumsum(lengths) - lengths
        self.ids[self.filled : self.filled + total] = [i for x in ids for i in x]
        self.n, self.filled = self.n + m, self.filled + total
        at = (h >> np.uint64(42)).astype(np.int64)
        todo = np.arange(m)
        while len(todo):
            free = self.keys[at[todo]] == 0
            put = todo[free]
            self.keys[at[put]] = h[put]
            self.entry[at[put]] = new[put]
            won = self.keys[at[todo]] == h[todo]
            todo = todo[~won]
            at[todo] = (at[todo] + 1) & (self.SLOTS - 1)

    def _entries(self, big: str, cps, starts, ends) -> tuple[np.ndarray, np.ndarray]:
        """The table's entry of each piece, and where the check beside the hash disagrees."""
        h, sign = self._hashes(cps, starts, ends)
        slot = self._slot(h)
        missing = np.flatnonzero(slot < 0)
        if len(missing):
            new, where = np.unique(h[missing], return_index=True)
            if self.n + len(new) > self.remembered and self.n > len(self.pre.whole):
                self._reset()
                return self._entries(big, cps, starts, ends)
            where = missing[where]
            merge = self.pre.merge
            self._insert(new, sign[where], [merge(big[a:b]) for a, b in zip(starts[where].tolist(), ends[where].tolist())])
            slot[missing] = self._slot(h[missing])
        entry = self.entry[slot]
        return entry, self.sign[entry] != sign

    def encode(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts one after another, number of ids of each text)."""
        return self._run(texts, True)

    def count_tokens(self, texts: list[str | None]) -> np.ndarray:
        return self._run(texts, False)[1]

    def _run(self, texts: list[str | None], with_ids: bool):
        texts = [t or "" for t in texts]
        cps, offsets = code_points(texts)
        odd = {k for s in self.pre.special for k, t in enumerate(texts) if s in t}
        odd |= set((np.searchsorted(offsets, np.flatnonzero(self.pre.classes[cps] == STRANGE), side="right") - 1).tolist())
        starts = self.pre.split(cps, offsets)
        ends = np.append(starts[1:], len(cps)) if len(starts) else starts
        first = np.searchsorted(starts, offsets)
        entry, doubt = self._entries("".join(texts), cps, starts, ends) if len(starts) else (np.zeros(0, np.int32), np.zeros(0, bool))
        if doubt.any():
            odd |= set((np.searchsorted(first, np.flatnonzero(doubt), side="right") - 1).tolist())
        each = self.count[entry].astype(np.int64)
        total = np.concatenate([[0], np.cumsum(each)])
        n = total[first[1:]] - total[first[:-1]]
        whole = {k: self.pre.library.encode(texts[k], add_special_tokens=False).ids for k in odd}
        ids = None
        if with_ids:
            ids = self.ids[np.repeat(self.at[entry] - total[:-1], each) + np.arange(total[-1])]
            if whole:
                bounds = total[first]
                ids = np.concatenate([np.array(whole[k], "<u4") if k in whole else ids[bounds[k] : bounds[k + 1]] for k in range(len(texts))])
        for k, x in whole.items():
            n[k] = len(x)
        return ids, n


def token_counts(docs: DataFrame, vocabulary: str | None = None, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit of every whole text."""
    path = vocabulary or vocabulary_path()
    proven = docs.sparkSession.sparkContext.broadcast(_proof(path))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = coder_for(path, proven.value)
        for whole in batches:
            for batch in text_slices(whole, "text", 1 << 20):
                n = coder.count_tokens(batch.column("text").to_pylist())
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id"), batch.column("n_bytes"), pa.array(n, pa.int64()), pa.array(n > limit, pa.bool_())],
                    names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
                )

    given = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"),
        F.coalesce(F.octet_length(F.col("text").cast("string")), F.lit(0)).cast("long").alias("n_bytes"),
    )
    return given.mapInArrow(count, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def _proof(path: str) -> tuple[np.ndarray, dict[str, int]]:
    """What is proven offline, once on the driver; its size is bounded by the vocabulary and Unicode."""
    pre = shared(path)
    return pre.classes, pre.whole


_coders: dict[str, Coder] = {}


def coder_for(path: str, proof) -> Coder:
    """One table for each worker process."""
    if path not in _coders:
        _coders[path] = Coder(PreTokens(path, proof))
    return _coders[path]


def query(spark, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"))
