"""Best-fit packing into sequences of several permitted lengths.

A document's tokens, with its end id, are one piece, or several of the largest permitted length and
a rest. Pieces are dealt by hash into shards of a bounded weight and each shard is packed by itself:
pieces in falling length go to the open bin that they leave the least room in; where none has room,
a bin of the least-cost permitted length that holds the piece is opened. The permitted lengths are
optimised jointly: for each of them as the largest length that is opened freely, the shard is packed
anew, every bin is then downsized to the least length that holds its contents, and the packing of
least total cost stays. Nothing is dropped or truncated.

``cost`` of a length c is ``fixed + c + c * c / attention``: tokens, a share for attention, and an
overhead for each sequence.

Defined results: null and empty texts are one piece of length 1 (the end id); repeated rows are packed
each; an empty table gives no rows; extra columns are ignored; a very long text is split into pieces
that all are placed; ties of length go by doc_id and piece, ties of room to the bin last touched.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.llm.common import materialize, table, text_slices
from edgesketch.llm.tokens import _proof, coder_for, vocabulary_path

LENGTHS = (1024, 2048, 4096, 8192)
FIXED, ATTENTION = 64.0, 65536.0
#: Weight (tokens, and 64 for each document) that a shard holds on average.
SHARD_WEIGHT = 8 << 20


def cost(length: int, fixed: float = FIXED, attention: float = ATTENTION) -> float:
    return fixed + length + length * length / attention


def _pack(sizes: list[int], openable: list[int], lengths: tuple[int, ...], price) -> list[tuple[int, int]]:
    """(bin, offset) of each size, given in falling order."""
    rooms: dict[int, list[int]] = {}
    mask, n, out, used = 0, 0, [], []
    choice = {}
    for size in sizes:
        fits = mask >> size
        if fits:
            room = size + ((fits & -fits).bit_length() - 1)
            stack = rooms[room]
            k = stack.pop()
            if not stack:
                mask &= ~(1 << room)
        else:
            if size not in choice:
                can = [c for c in openable if c >= size] or [min(c for c in lengths if c >= size)]
                choice[size] = min(can, key=lambda c: (price(c) / c, c))
            room, k = choice[size], n
            n += 1
            used.append(0)
        out.append((k, used[k]))
        used[k] += size
        left = room - size
        if left:
            rooms.setdefault(left, []).append(k)
            mask |= 1 << left
    return out


def pack_shard(sizes: list[int], lengths: tuple[int, ...] = LENGTHS, fixed: float = FIXED, attention: float = ATTENTION) -> tuple[list[tuple[int, int]], list[int], float]:
    """Places of sizes in falling order, the length of each bin, and the total cost."""
    lengths = tuple(sorted(lengths))
    price = lambda c: cost(c, fixed, attention)
    best = None
    for most in lengths:
        places = _pack(sizes, [c for c in lengths if c <= most], lengths, price)
        filled = [0] * (max((k for k, _ in places), default=-1) + 1)
        for (k, _), s in zip(places, sizes):
            filled[k] += s
        fitted = [next(c for c in lengths if c >= f) for f in filled]
        total = sum(map(price, fitted))
        if best is None or total < best[2]:
            best = places, fitted, total
    return best


PACKED = "doc_id long, piece int, start long, length int, bin_id long, bin_length int, offset int"


def pack(sized: DataFrame, lengths: tuple[int, ...] = LENGTHS, fixed: float = FIXED, attention: float = ATTENTION, shard_weight: int = SHARD_WEIGHT) -> DataFrame:
    """Packs (doc_id, n_tokens) rows; one row for each piece with its bin, the bin's length and offset."""
    total = sized.agg(F.sum(F.col("n_tokens") + 64).alias("w")).first().w or 0
    shards, most = max(1, -(-total // shard_weight)), max(lengths)
    pieces = sized.select("doc_id", "n_tokens", F.posexplode(F.sequence(F.lit(0).cast("long"), F.col("n_tokens") - 1, F.lit(most).cast("long"))).alias("piece", "start"))
    pieces = pieces.select(
        "doc_id", "piece", "start", F.least(F.lit(most).cast("long"), F.col("n_tokens") - F.col("start")).cast("int").alias("length"),
        F.pmod(F.xxhash64("doc_id", "piece", "n_tokens"), F.lit(shards)).alias("shard"),
    )

    def place(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["length", "doc_id", "piece"], ascending=[False, True, True], kind="stable", ignore_index=True)
        places, fitted, _ = pack_shard(part["length"].tolist(), lengths, fixed, attention)
        base = int(part["shard"].iloc[0]) << 32
        part["bin_id"] = [base + k for k, _ in places]
        part["bin_length"] = [fitted[k] for k, _ in places]
        part["offset"] = [o for _, o in places]
        return part[["doc_id", "piece", "start", "length", "bin_id", "bin_length", "offset"]]

    return pieces.groupBy("shard").applyInPandas(place, PACKED)


def token_sizes(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """(doc_id, n_tokens) with the end id, counted by the whole-token shortcut."""
    path = vocabulary or vocabulary_path()
    proven = docs.sparkSession.sparkContext.broadcast(_proof(path))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = coder_for(path, proven.value)
        for whole in batches:
            for batch in text_slices(whole, "text", 1 << 20):
                n = coder.count_tokens(batch.column("text").to_pylist()) + 1
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64())], names=["doc_id", "n_tokens"])

    given = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return given.mapInArrow(count, "doc_id long, n_tokens long")


def pack_documents(docs: DataFrame, lengths: tuple[int, ...] = LENGTHS, vocabulary: str | None = None) -> DataFrame:
    """Counts the tokens once, keeps the counts in the shared folder, and packs all pieces."""
    return pack(materialize(token_sizes(docs, vocabulary), "sizes"), lengths)


def query(spark, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))
