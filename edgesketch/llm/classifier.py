"""Quality classifier: supervised subword embeddings, trained by NumPy stochastic gradient descent.

The features of a text are hashed: its words, pairs of neighbouring words (a word that repeats the one
before it is the pair "same"), and the character 3- and 4-grams of words with their ends. Each
bucket has a learned vector; a document is the average over its features, and a softmax over two
outputs gives the score. Vectors and outputs are learned together.

Training takes at most ``train_rows`` labelled rows of each class, those of least hash, whole texts;
that bound is the parameter. Scoring folds the softmax's weights into one number for each bucket, so
a text costs one table look-up for each feature. The model, of a fixed size, is broadcast.

Defined results: null and empty texts, and those without a word, score 0; rows without a label or
of a null one are not learned from; with labels of one class only every text scores that class's
label; without labels 0.5; repeated rows get a row each; an empty table gives no rows; extra columns
are ignored; very long texts are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.llm.common import table, text_slices
from edgesketch.llm.tokens import code_points

BUCKETS = 1 << 18
DIMENSIONS = 8
TRAIN_ROWS = 1_000
EPOCHS, RATE, BATCH = 6, 2.0, 32
THRESHOLD = 0.3
_A, _B, _C, _D = (np.uint32(x) for x in (0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F))


def _bucket(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
    return (h ^ (h >> np.uint32(13))) & np.uint32(BUCKETS - 1)


def features(texts: list[str | None]) -> tuple[list[np.ndarray], list[np.ndarray], np.ndarray]:
    """Buckets by kind of feature, and the text of each; kinds come one after another."""
    cps, offsets = code_points([t or "" for t in texts])
    n = len(cps)
    if not n:
        return [], [], offsets
    space = (cps <= 32) & ((cps == 32) | ((cps >= 9) & (cps <= 13)))
    c = np.where(space, np.uint32(32), cps)
    # words
    edge = np.ones(n, bool)
    np.not_equal(space[1:], space[:-1], out=edge[1:])
    edge[offsets[:-1][offsets[:-1] < n]] = True
    begin = np.flatnonzero(edge)
    end = np.append(begin[1:], n)
    words = ~space[begin]
    begin, end = begin[words], end[words]
    sums = np.zeros(n + 1, np.uint32)
    place = np.arange(n) - np.repeat(np.flatnonzero(edge), np.diff(np.append(np.flatnonzero(edge), n)))
    with np.errstate(over="ignore"):
        np.cumsum(((c + _A) * (c ^ _B)) * (place.astype(np.uint32) * _C + np.uint32(1)) ^ (c * _D), out=sums[1:], dtype=np.uint32)
        word = (sums[end] - sums[begin]) * _A + (end - begin).astype(np.uint32)
        owner = np.searchsorted(offsets, begin, side="right") - 1
        pair = (word[:-1] * _B) ^ (word[1:] * _C)
        pair[word[:-1] == word[1:]] = np.uint32(1)
        paired = owner[:-1] == owner[1:]
        # character n-grams within words, with the blank before or after
        kinds, owners = [_bucket(word), _bucket(pair[paired] ^ _D)], [owner, owner[1:][paired]]
        text = np.repeat(np.arange(len(texts)), np.diff(offsets))
        for size in (3, 4):
            if n < size:
                continue
            m = n - size + 1
            h = c[:m] * _A
            for k, by in zip(range(1, size), (_B, _C, _D)):
                h = (h ^ (h >> np.uint32(16))) + c[k : k + m] * by
            good = text[:m] == text[size - 1 :]
            for k in range(1, size - 1):
                good &= ~space[k : k + m]
            kinds.append(_bucket(h[good] ^ np.uint32(size)))
            owners.append(text[:m][good])
    return kinds, owners, offsets


@dataclass
class Model:
    """One number for each bucket; a text's logit is their mean. ``constant`` is the score if nothing was learned."""

    weights: np.ndarray | None
    constant: float = 0.5

    def score(self, texts: list[str | None]) -> np.ndarray:
        kinds, owners, _ = features(texts)
        total, count = np.zeros(len(texts)), np.zeros(len(texts))
        for b, o in zip(kinds, owners):
            if len(b):
                total += np.bincount(o, self.weights[b] if self.weights is not None else None, len(texts))
                count += np.bincount(o, minlength=len(texts))
        if self.weights is None:
            return np.where(count > 0, self.constant, 0.0)
        return np.where(count > 0, 1 / (1 + np.exp(-np.clip(total / np.maximum(count, 1), -50, 50))), 0.0)


def train(texts: list[str], labels: list[int], dimensions: int = DIMENSIONS, epochs: int = EPOCHS, rate: float = RATE, seed: int = 7) -> Model:
    """Learns bucket vectors and the softmax by stochastic gradient descent over small batches."""
    if len(set(labels)) < 2:
        return Model(None, float(labels[0]) if labels else 0.5)
    rows: list[tuple[np.ndarray, np.ndarray]] = []
    for at in range(0, len(texts), 200):
        kinds, owners, _ = features(texts[at : at + 200])
        if not kinds:
            rows += [(np.zeros(0, np.int64), np.zeros(0, np.float32))] * len(texts[at : at + 200])
            continue
        code, n = np.unique(np.concatenate(owners).astype(np.int64) * BUCKETS + np.concatenate(kinds), return_counts=True)
        cuts = np.searchsorted(code, np.arange(len(texts[at : at + 200]) + 1) * BUCKETS)
        for a, b in zip(cuts[:-1], cuts[1:]):
            rows.append((code[a:b] & (BUCKETS - 1), (n[a:b] / max(1, n[a:b].sum())).astype(np.float32)))
    y = np.array(labels)
    rng = np.random.default_rng(seed)
    vectors = rng.uniform(-1 / dimensions, 1 / dimensions, (BUCKETS, dimensions)).astype(np.float32)
    outputs = np.zeros((dimensions, 2), np.float32)
    outputs[:] = rng.normal(0, 0.5, outputs.shape)
    steps, step = epochs * -(-len(rows) // BATCH), 0
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for at in range(0, len(order), BATCH):
            some = [i for i in order[at : at + BATCH].tolist() if len(rows[i][0])]
            if not some:
                continue
            index = np.concatenate([rows[i][0] for i in some])
            share = np.concatenate([rows[i][1] for i in some])
            sizes = np.array([len(rows[i][0]) for i in some])
            head = np.cumsum(sizes) - sizes
            hidden = np.add.reduceat(vectors[index] * share[:, None], head)
            logits = hidden @ outputs
            p = np.exp(logits - logits.max(axis=1, keepdims=True))
            p /= p.sum(axis=1, keepdims=True)
            p[np.arange(len(some)), y[some]] -= 1
            now = rate * (1 - step / steps)
            step += 1
            back = p @ outputs.T
            outputs -= (now / len(some)) * (hidden.T @ p)
            used, where = np.unique(index, return_inverse=True)
            change = np.repeat(back, sizes, axis=0) * share[:, None]
            for d in range(dimensions):
                # a feature's share of one document is small, so its vector takes larger steps
                vectors[used, d] -= now * 8 * np.bincount(where, change[:, d], len(used)).astype(np.float32)
    return Model((vectors @ (outputs[:, 1] - outputs[:, 0])).astype(np.float32))


def training_rows(docs: DataFrame, labels: DataFrame, column: str = "quality", train_rows: int = TRAIN_ROWS) -> tuple[list[str], list[int]]:
    """At most ``train_rows`` whole texts of each class, of rows that are not held out.

    A doc_id with several labels or texts takes the least of each, so that the model depends on no order of rows.
    """
    usable = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(column).cast("int").alias("y")).where(F.col("y").isin(0, 1) & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.min("y").alias("y"))
    drawn = [usable.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(train_rows) for y in (0, 1)]
    chosen = [(r.doc_id, r.y) for part in drawn for r in part.collect()]  # bounded by train_rows
    if not chosen:
        return [], []
    small = docs.sparkSession.createDataFrame(chosen, "doc_id long, y int")
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(small), "doc_id").groupBy("doc_id", "y").agg(F.min("text").alias("text"))
    got = sorted((r.doc_id, r.y, r.text or "") for r in found.toLocalIterator())
    return [t for _, _, t in got], [y for _, y, _ in got]


def held_out(doc_id):
    """crc32 of the id as text, modulo 5, is 0."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def classify(docs: DataFrame, labels: DataFrame, column: str = "quality", threshold: float = THRESHOLD, train_rows: int = TRAIN_ROWS) -> DataFrame:
    """doc_id, held_out, score and predicted of every row; equal texts score alike, repeated rows stay."""
    model = docs.sparkSession.sparkContext.broadcast(train(*training_rows(docs, labels, column, train_rows)))

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text", 1 << 20):
                s = model.value.score(batch.column("text").to_pylist())
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(s), pa.array((s >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    given = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return given.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(look, "doc_id long, held_out boolean, score double, predicted int")


def query(spark, sf_dir: str) -> DataFrame:
    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
