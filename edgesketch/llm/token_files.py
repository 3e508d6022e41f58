"""Token-ID files: fixed-size id blocks as bit or byte planes, each plane compressed with zstandard.

The texts are range-partitioned by doc_id and sorted, so that the files together hold the ids in
ascending doc_id order; each text is encoded by the library through the pre-token table of
``tokens``, and the end id follows it. A task writes one file, streaming: ids gather in a segment of
about ``segment_ids`` ids that holds whole documents (a longer one stands alone). Within a segment,
blocks of ``block_ids`` ids are transposed into 32 bit planes or 4 byte planes; each plane is one
zstandard frame, an all-zero plane takes no bytes. The chunk index (where each plane of each block
lies) stands beside the payload, so any block can be read without the others.

Files are Parquet containers of such segments, one row each, so that Spark's commit protocol covers
lost and repeated tasks and any store works. Where a file begins in the whole stream follows from
the id totals per file, of which there are as many as files.

Defined results: null and empty texts are the end id alone; a null doc_id sorts first; repeated rows
are written each; an empty table gives no rows; extra columns are ignored; very long texts are
encoded whole.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgesketch.llm.common import partitions_for, scratch_path, table, text_slices
from edgesketch.llm.tokens import _proof, coder_for, vocabulary_path

END_ID = 2
BLOCK_IDS = 16_384
SEGMENT_IDS = 1 << 20

SEGMENT = "file_no int, segment int, first long, n_ids long, block_ids int, planes string, doc_ids array<long>, lengths array<long>, plane_at array<long>, payload binary"


def to_planes(ids: np.ndarray, planes: str) -> list[bytes]:
    """The planes of one block of 32-bit ids, from the lowest bit or byte on."""
    octets = ids.astype("<u4").view(np.uint8).reshape(-1, 4)
    if planes == "byte":
        return [octets[:, k].tobytes() for k in range(4)]
    bits = np.unpackbits(octets, axis=1, bitorder="little")
    return [np.packbits(bits[:, k]).tobytes() if bits[:, k].any() else b"" for k in range(32)]


def from_planes(parts: list[bytes], n: int, planes: str) -> np.ndarray:
    if planes == "byte":
        octets = np.zeros((n, 4), np.uint8)
        for k, part in enumerate(parts):
            if part:
                octets[:, k] = np.frombuffer(part, np.uint8)
        return octets.reshape(-1).view("<u4")
    bits = np.zeros((n, 32), np.uint8)
    for k, part in enumerate(parts):
        if part:
            bits[:, k] = np.unpackbits(np.frombuffer(part, np.uint8), count=n)
    return np.packbits(bits, axis=1, bitorder="little").reshape(-1).view("<u4")


def pack_ids(ids: np.ndarray, planes: str = "byte", block_ids: int = BLOCK_IDS, level: int = 1) -> tuple[bytes, list[int]]:
    """(payload, index): the index has the start of every plane of every block, and the end."""
    import zstandard

    squeeze = zstandard.ZstdCompressor(level=level)
    out, at, size = [], [0], 0
    for k in range(0, len(ids), block_ids):
        for part in to_planes(ids[k : k + block_ids], planes):
            frame = squeeze.compress(part) if part.strip(b"\0") else b""
            out.append(frame)
            size += len(frame)
            at.append(size)
    return b"".join(out), at


def unpack_block(payload: bytes, at: list[int], block: int, n_ids: int, planes: str = "byte", block_ids: int = BLOCK_IDS) -> np.ndarray:
    """The ids of one block, by the index alone."""
    import zstandard

    each = 4 if planes == "byte" else 32
    n = min(block_ids, n_ids - block * block_ids)
    grow = zstandard.ZstdDecompressor()
    cut = [payload[at[i] : at[i + 1]] for i in range(block * each, (block + 1) * each)]
    return from_planes([grow.decompress(x) if x else b"" for x in cut], n, planes)


def unpack_ids(payload: bytes, at: list[int], n_ids: int, planes: str = "byte", block_ids: int = BLOCK_IDS) -> np.ndarray:
    blocks = -(-n_ids // block_ids)
    return np.concatenate([unpack_block(payload, at, k, n_ids, planes, block_ids) for k in range(blocks)]) if blocks else np.zeros(0, "<u4")


def write(docs: DataFrame, path: str, vocabulary: str | None = None, end_id: int = END_ID, planes: str = "byte", block_ids: int = BLOCK_IDS, segment_ids: int = SEGMENT_IDS) -> None:
    """Writes the ids of all documents in ascending doc_id order: null ids first, rows of one id by a hash of their text, repeated rows each."""
    spark = docs.sparkSession
    source = vocabulary or vocabulary_path()
    proven = spark.sparkContext.broadcast(_proof(source))
    end = np.array([end_id], "<u4")

    def row(file_no, segment, first, ids, doc_ids, lengths):
        payload, at = pack_ids(ids, planes, block_ids)
        cols = [[file_no], [segment], [first], [len(ids)], [block_ids], [planes], [doc_ids], [lengths], [at], [payload]]
        kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary()]
        names = [x.split()[0] for x in SEGMENT.split(", ")]
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = coder_for(source, proven.value)
        body, doc_ids, lengths, held, first, segment, file_no = [], [], [], 0, 0, 0, 0
        for whole in batches:
            for batch in text_slices(whole, "text", 1 << 20):
                file_no = batch.column("file_no")[0].as_py()
                all_ids, n = coder.encode(batch.column("text").to_pylist())
                ends = np.cumsum(n).tolist()
                for doc_id, k, stop in zip(batch.column("doc_id").to_pylist(), n.tolist(), ends):
                    body += (all_ids[stop - k : stop], end)
                    doc_ids.append(doc_id)
                    lengths.append(k + 1)
                    held += lengths[-1]
                    if held >= segment_ids:
                        yield row(file_no, segment, first, np.concatenate(body), doc_ids, lengths)
                        first, segment = first + held, segment + 1
                        body, doc_ids, lengths, held = [], [], [], 0
        if doc_ids:
            yield row(file_no, segment, first, np.concatenate(body), doc_ids, lengths)

    given = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    dealt = given.repartitionByRange(partitions_for(spark), F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"))
    dealt.select("doc_id", "text", F.spark_partition_id().alias("file_no")).mapInArrow(encode, SEGMENT).write.option("compression", "none").parquet(path)


def segments(spark: SparkSession, path: str) -> DataFrame:
    """The segments with ``base``, the ids of all files before theirs."""
    read = spark.read.parquet(path)
    totals = read.groupBy("file_no").agg(F.sum("n_ids").alias("n")).orderBy("file_no").collect()  # a row for each file
    bases, at = [], 0
    for r in totals:
        bases.append((r.file_no, at))
        at += r.n
    return read.join(F.broadcast(spark.createDataFrame(bases, "file_no int, base long")), "file_no")


def digests(spark: SparkSession, path: str) -> DataFrame:
    """Reads the files back: doc_id, start, n_tokens and the crc32 of each document's ids."""

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                ids = unpack_ids(r["payload"], r["plane_at"], r["n_ids"], r["planes"], r["block_ids"])
                body = memoryview(ids.tobytes())
                ends = np.cumsum(r["lengths"])
                starts = ends - np.array(r["lengths"])
                crc = [zlib.crc32(body[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist())]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(r["doc_ids"], pa.int64()), pa.array(starts + r["base"] + r["first"], pa.int64()), pa.array(r["lengths"], pa.int64()), pa.array(crc, pa.int64())],
                    names=["doc_id", "start", "n_tokens", "ids_crc32"],
                )

    return segments(spark, path).mapInArrow(look, "doc_id long, start long, n_tokens long, ids_crc32 long")


def query(spark, sf_dir: str) -> DataFrame:
    path = scratch_path(spark, "token-files")
    write(table(spark, sf_dir, "documents"), path)
    return digests(spark, path)
