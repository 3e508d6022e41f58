"""Vertex batching: how endpoint rows cross the network, as raw ids or as sketch deltas.

A map task gathers the endpoint rows of its partition by vertex. Under the hybrid policy a vertex with
at least gamma of a full batch is sketched there and crosses as one delta; the rest crosses as raw ids
and is sketched where it arrives. ``raw`` ships ids only, ``delta`` bodies only, ``tree`` is the
two-level range routing of raw ids. Deltas of a partition cap what a hub vertex sends: one body.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.functions.sampler import SamplerKernel, SketchParams
from edgesketch.tables import parts

#: Rows that a map task gathers before it routes them: what bounds its memory beside one block of bodies.
GATHER_ROWS = 1 << 20
#: Bytes of bodies that a task holds at once.
BLOCK_BYTES = 64 << 20


@dataclass(frozen=True)
class BatchPolicy:
    mode: str = "hybrid"
    alpha: float = 1.0
    gamma: float = 0.5
    unchecked: bool = False

    def __post_init__(self):
        if self.mode not in ("raw", "delta", "hybrid", "tree"):
            raise ValueError(f"unknown policy: {self.mode}")
        if not self.unchecked and (self.alpha < 1 or not 0 < self.gamma <= 0.5):
            raise ValueError("alpha is at least 1, gamma in (0, 1/2]")

    def least(self, params: SketchParams) -> int:
        """Updates of a vertex from which it crosses as a delta."""
        if self.mode == "delta":
            return 1
        if self.mode in ("raw", "tree"):
            return np.iinfo(np.int64).max
        return max(1, int(np.ceil(self.gamma * params.capacity(self.alpha))))


ROUTED = "vertex long, eid long, n int, body binary"


def _binary_rows(body: np.ndarray) -> pa.Array:
    """One binary cell per row, from one buffer and its offsets."""
    n, width = len(body), body.shape[1] * 8
    offsets = np.arange(n + 1, dtype=np.int64) * width
    data = pa.py_buffer(np.ascontiguousarray(body))
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), n, [None, pa.py_buffer(offsets), data]).cast(pa.binary())


def _gathered(batches):
    """The (vertex, eid) rows of a map task, as much at once as it routes."""
    held, size = [], 0
    for batch in batches:
        held.append((batch.column("vertex").to_numpy(), batch.column("eid").to_numpy()))
        size += batch.num_rows
        if size >= GATHER_ROWS:
            yield tuple(map(np.concatenate, zip(*held)))
            held, size = [], 0
    if held:
        yield tuple(map(np.concatenate, zip(*held)))


def _by_range(ends: DataFrame, policy: BatchPolicy) -> DataFrame:
    if policy.mode == "tree":
        # two passes: ranges of vertices, then sorted within them
        return ends.repartitionByRange(max(2, int(parts(ends.sparkSession) ** 0.5)), "vertex").sortWithinPartitions("vertex")
    return ends


def route(ends: DataFrame, params: SketchParams, policy: BatchPolicy = BatchPolicy()) -> DataFrame:
    """(vertex, eid, n, body): raw rows have an eid, deltas a body of all samplers over n updates. Narrow."""
    least = policy.least(params)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = SamplerKernel(params)
        block = max(1, BLOCK_BYTES // params.vertex_bytes)
        names = ["vertex", "eid", "n", "body"]
        for vertex, eid in _gathered(batches):
            order = np.argsort(vertex, kind="stable")
            vertex, eid = vertex[order], eid[order]
            who, first, n = np.unique(vertex, return_index=True, return_counts=True)
            full = n >= least
            raw = np.repeat(~full, n)
            if raw.any():
                k = int(raw.sum())
                yield pa.RecordBatch.from_arrays([pa.array(vertex[raw]), pa.array(eid[raw]), pa.array(np.ones(k, np.int32)), pa.nulls(k, pa.binary())], names=names)
            sent = np.flatnonzero(full)
            for at in range(0, len(sent), block):
                some = sent[at : at + block]
                group = np.repeat(np.arange(len(some)), n[some])
                index = np.concatenate([np.arange(first[i], first[i] + n[i]) for i in some])
                body = kernel.sketch(group, eid[index].view(np.uint64), len(some))
                yield pa.RecordBatch.from_arrays([pa.array(who[some]), pa.nulls(len(some), pa.int64()), pa.array(n[some].astype(np.int32)), _binary_rows(body)], names=names)

    ends = _by_range(ends, policy)
    if policy.mode in ("raw", "tree"):  # nothing is sketched here, so nothing leaves the JVM
        return ends.select("vertex", "eid", F.lit(1).alias("n"), F.lit(None).cast("binary").alias("body"))
    return ends.mapInArrow(work, ROUTED)


def merge_routed(routed: DataFrame, params: SketchParams, mode: str = "hybrid") -> DataFrame:
    """(vertex, body) of all samplers: the one shuffle by vertex, then bodies xored and raw ids applied in a sorted stream.

    Equal rows cancel in pairs by an aggregate that keeps that partitioning, so that repeated updates of
    an edge are neither sorted nor leave the JVM. Deltas are keys of it too: two equal bodies cancel like
    two equal ids. A stream of deltas alone has too few equal rows for it to pay.
    """
    dealt = routed.select("vertex", "eid", "body").repartition(parts(routed.sparkSession), "vertex")
    if mode in ("raw", "tree"):
        dealt = dealt.groupBy("vertex", "eid").agg(F.count(F.lit(1)).alias("n")).where("n % 2 = 1").select("vertex", "eid", F.lit(None).cast("binary").alias("body"))
    elif mode == "hybrid":
        dealt = dealt.groupBy("vertex", "eid", "body").agg(F.count(F.lit(1)).alias("n")).where("n % 2 = 1").select("vertex", "eid", "body")
    return dealt.sortWithinPartitions("vertex").mapInArrow(_reducer(params), "vertex long, body binary")


def sketched_rows(ends: DataFrame, params: SketchParams, policy: BatchPolicy = BatchPolicy()) -> DataFrame:
    """(vertex, body) of endpoint rows under a policy."""
    return merge_routed(route(ends, params, policy), params, policy.mode)


def body_words(column, words: int) -> np.ndarray:
    """Rows of 64-bit words of a binary column without nulls whose cells are all of that size."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros((0, words), np.uint64)
    offsets = np.frombuffer(column.buffers()[1], np.int64 if pa.types.is_large_binary(column.type) else np.int32)
    first = int(offsets[column.offset])
    return np.frombuffer(column.buffers()[2], np.uint8)[first : first + len(column) * words * 8].view(np.uint64).reshape(len(column), words)


def _reducer(params: SketchParams):
    block = max(1, BLOCK_BYTES // params.vertex_bytes)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = SamplerKernel(params)
        tail = None  # the last vertex's body, as more of its rows may come

        def emit(who, body):
            keep = body.any(axis=1)
            who, body = (who, body) if keep.all() else (who[keep], body[keep])
            step = max(1, (8 << 20) // params.vertex_bytes)
            for at in range(0, len(who), step):
                yield pa.RecordBatch.from_arrays([pa.array(who[at : at + step]), _binary_rows(body[at : at + step])], names=["vertex", "body"])

        for batch in batches:
            vertex = batch.column("vertex").to_numpy()
            eid = batch.column("eid").fill_null(-1).to_numpy()
            cells = batch.column("body")
            who, first = np.unique(vertex, return_index=True)
            bounds = np.append(first, len(vertex))
            for at in range(0, len(who), block):
                some = who[at : at + block]
                a, b = int(bounds[at]), int(bounds[min(at + block, len(who))])
                group = np.searchsorted(some, vertex[a:b])
                body = kernel.zeros(len(some))
                if tail is not None:
                    if some[0] == tail[0]:
                        body[0] ^= tail[1]
                    else:
                        yield from emit(np.array([tail[0]]), tail[1][None, :])
                    tail = None
                raw = eid[a:b] >= 0
                if raw.any():
                    kernel.toggle(body, group[raw], eid[a:b][raw].view(np.uint64))
                for k in np.flatnonzero(~raw).tolist():
                    body[group[k]] ^= np.frombuffer(cells[a + k].as_buffer(), np.uint64)
                tail = (int(some[-1]), body[-1].copy())
                if len(some) > 1:
                    yield from emit(some[:-1], body[:-1])
        if tail is not None:
            yield from emit(np.array([tail[0]]), tail[1][None, :])

    return work


def traffic(routed: DataFrame, params: SketchParams) -> DataFrame:
    """What crosses the network: raw ids and deltas with their bytes, and the updates that each stands for."""
    delta = F.col("body").isNotNull()
    return routed.agg(
        F.count(F.when(~delta, 1)).alias("raw_ids"), F.count(F.when(delta, 1)).alias("deltas"),
        F.coalesce(F.sum(F.when(delta, F.col("n"))), F.lit(0)).alias("updates_in_deltas"),
        (F.count(F.when(~delta, 1)) * 8).alias("raw_bytes"), (F.count(F.when(delta, 1)) * params.vertex_bytes).alias("delta_bytes"),
    )


def counted_traffic(ends: DataFrame, params: SketchParams, policy: BatchPolicy = BatchPolicy()) -> DataFrame:
    """``traffic`` of what ``route`` makes of these rows, told from the sizes of its batches alone: no body is sketched for it."""
    least = policy.least(params)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for vertex, _ in _gathered(batches):
            _, n = np.unique(vertex, return_counts=True)
            full = n >= least
            told = (n[~full].sum(), full.sum(), n[full].sum())
            yield pa.RecordBatch.from_arrays([pa.array([int(x)]) for x in told], names=["raw_ids", "deltas", "updates_in_deltas"])

    ends = _by_range(ends, policy)
    if policy.mode in ("raw", "tree"):
        each = ends.agg(F.count(F.lit(1)).alias("raw_ids"), F.lit(0).cast("long").alias("deltas"), F.lit(0).cast("long").alias("updates_in_deltas"))
    else:
        each = ends.mapInArrow(work, "raw_ids long, deltas long, updates_in_deltas long")
    told = each.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("raw_ids", "deltas", "updates_in_deltas")))
    return told.select("*", (F.col("raw_ids") * 8).alias("raw_bytes"), (F.col("deltas") * params.vertex_bytes).alias("delta_bytes"))
