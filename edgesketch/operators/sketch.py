"""The graph sketch: layout B, a row for each vertex and a column for each sampler, with the metadata that merging checks."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgesketch.functions.sampler import SketchParams
from edgesketch.operators.batching import BatchPolicy, _binary_rows, body_words, sketched_rows
from edgesketch.sources.updates import endpoints
from edgesketch.tables import parts, scratch_path, scratch_scope, shuffles_released


def sampler_column(copy: int, sampler: int) -> str:
    return f"c{copy}_s{sampler}"


def _columns(params: SketchParams) -> list[str]:
    return [sampler_column(c, s) for c in range(params.copies) for s in range(params.samplers)]


def write_bodies(rows: DataFrame, params: SketchParams, path: str, mode: str = "error") -> None:
    """Writes (vertex, body) rows with a column for each sampler, so that a round reads one of them; one file a task."""
    n = params.body_bytes
    cut = [F.substr("body", F.lit(1 + k * n), F.lit(n)).alias(name) for k, name in enumerate(_columns(params))]
    # bodies are all different, so a dictionary only costs
    with shuffles_released(rows.sparkSession):
        rows.select("vertex", *cut).write.mode(mode).option("compression", "lz4").option("parquet.enable.dictionary", "false").parquet(path)


def read_bodies(spark: SparkSession, params: SketchParams, path: str, more: str = "") -> DataFrame:
    """(vertex, body of all samplers) and the partition columns named in ``more``."""
    wide = spark.read.schema(_schema(params) + more).parquet(path)
    kept = [c for c in wide.columns if c not in _columns(params)]
    return wide.select(*kept, F.concat(*_columns(params)).alias("body"))


def _schema(params: SketchParams) -> str:
    return ", ".join(["vertex long", *(f"{name} binary" for name in _columns(params))])


@dataclass
class GraphSketch:
    """Bodies at ``path``; a round reads one sampler by column pruning."""

    spark: SparkSession
    params: SketchParams
    path: str
    epoch: int = 0
    meta: dict = field(default_factory=dict)

    @classmethod
    def build(cls, updates: DataFrame, params: SketchParams, policy: BatchPolicy = BatchPolicy(), path: str | None = None, epoch: int = 0) -> GraphSketch:
        """Sketches a stream in one pass with one shuffle."""
        spark = updates.sparkSession
        rows = sketched_rows(endpoints(updates), params, policy)
        return cls._write(spark, rows, params, path or scratch_path(spark, "sketch"), epoch)

    @classmethod
    def _write(cls, spark, rows: DataFrame, params: SketchParams, path: str, epoch: int) -> GraphSketch:
        write_bodies(rows, params, path)
        return cls(spark, params, path, epoch)

    @property
    def wide(self) -> DataFrame:
        return self.spark.read.schema(_schema(self.params)).parquet(self.path)

    @property
    def bodies(self) -> DataFrame:
        """(vertex, body) of all samplers."""
        return read_bodies(self.spark, self.params, self.path)

    @property
    def table(self) -> DataFrame:
        """(vertex, body, copy, sampler), a row for each sampler."""
        p = self.params
        each = [F.struct(F.col(sampler_column(c, s)).alias("body"), F.lit(c).alias("copy"), F.lit(s).alias("sampler")) for c in range(p.copies) for s in range(p.samplers)]
        return self.wide.select("vertex", F.explode(F.array(*each)).alias("x")).select("vertex", "x.*")

    def sampler(self, copy: int, sampler: int) -> DataFrame:
        """(vertex, body) of one sampler; other columns are not read."""
        return self.wide.select("vertex", F.col(sampler_column(copy, sampler)).alias("body"))

    def merge(self, other: GraphSketch) -> GraphSketch:
        """The sketch of both streams: bodies xored. Both must have equal parameters; over GF(2) this also subtracts."""
        if self.params.key() != other.params.key():
            raise ValueError("sketches of different parameters can't be added")
        rows = xor_bodies(self.bodies.unionByName(other.bodies), ["vertex"])
        return self._write(self.spark, rows, self.params, scratch_path(self.spark, "sketch"), max(self.epoch, other.epoch))

    subtract = merge

    def advance(self, updates: DataFrame, epoch: int, policy: BatchPolicy = BatchPolicy(), outer: int = 0) -> GraphSketch:
        """The sketch at a later epoch. An epoch is taken once: xor is not idempotent, so a repeat is refused.

        Bodies of the updates are xored in as they come, without a table of their own; ``outer`` as in ``scratch_path``.
        """
        if epoch <= self.epoch:
            raise ValueError(f"epoch {epoch} is in the sketch already")
        more = sketched_rows(endpoints(updates), self.params, policy)
        rows = xor_bodies(self.bodies.unionByName(more), ["vertex"])
        return self._write(self.spark, rows, self.params, scratch_path(self.spark, "sketch", outer), epoch)

    def is_current(self, at_seq: int) -> bool:
        return self.epoch >= at_seq

    def write(self, path: str) -> None:
        write_bodies(self.bodies, self.params, f"{path}/bodies")
        p = self.params
        row = (p.v_count, p.variant, p.copies, p.samplers, p.columns, p.levels, p.seed, p.hash_family, p.first_copy, self.epoch)
        names = "v_count long, variant string, copies int, samplers int, columns int, levels int, seed long, hash_family string, first_copy int, epoch long"
        self.spark.createDataFrame([row], names).write.parquet(f"{path}/meta")

    @classmethod
    def read(cls, spark: SparkSession, path: str) -> GraphSketch:
        m = spark.read.parquet(f"{path}/meta").first()
        return cls(spark, SketchParams(m.v_count, m.variant, m.copies, m.samplers, m.columns, m.levels, m.seed, m.hash_family, m.first_copy), f"{path}/bodies", m.epoch)

    def components(self, **how) -> DataFrame:
        from edgesketch.operators.forest import spanning_forest

        return spanning_forest(self, **how).labels

    def spanning_forest(self, **how):
        from edgesketch.operators.forest import spanning_forest

        return spanning_forest(self, **how)


def xor_bodies(rows: DataFrame, keys: list[str], dealt: bool = True) -> DataFrame:
    """Xors the bodies of equal keys: combined within each batch, shuffled by key, then in a sorted stream."""
    spark = rows.sparkSession
    kinds = [(k, rows.schema[k].dataType.simpleString()) for k in keys]
    ddl = ", ".join(f"{k} {t}" for k, t in kinds) + ", body binary"
    combine = _xor_runs(keys)
    rows = rows.select(*keys, "body").mapInArrow(combine, ddl)
    if dealt:
        rows = rows.repartition(parts(spark), *keys)
    return rows.sortWithinPartitions(*keys).mapInArrow(combine, ddl)


def _xor_runs(keys: list[str]):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tail = None
        for whole in batches:
            if not whole.num_rows:
                continue
            words = len(whole.column("body")[0].as_buffer()) // 8
            for at in range(0, whole.num_rows, step := max(1, (8 << 20) // (8 * words))):
                batch = whole.slice(at, step)
                body = body_words(batch.column("body"), words)
                cols = [batch.column(k).to_numpy() for k in keys]
                order = np.lexsort(cols[::-1])
                cols, body = [c[order] for c in cols], body[order]
                edge = np.ones(len(body), bool)
                edge[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in cols])
                head = np.flatnonzero(edge)
                body = np.bitwise_xor.reduceat(body, head, axis=0)
                cols = [c[head] for c in cols]
                if tail is not None:
                    if all(c[0] == t for c, t in zip(cols, tail[0])):
                        body[0] ^= tail[1]
                    else:
                        yield pa.RecordBatch.from_arrays([*(pa.array([t]).cast(k) for t, k in zip(tail[0], tail[2])), _binary_rows(tail[1][None, :])], names=[*keys, "body"])
                tail = ([c[-1] for c in cols], body[-1].copy(), [batch.schema.field(k).type for k in keys])
                if len(head) > 1:
                    yield pa.RecordBatch.from_arrays([*(pa.array(c[:-1]).cast(t) for c, t in zip(cols, tail[2])), _binary_rows(body[:-1])], names=[*keys, "body"])
        if tail is not None:
            yield pa.RecordBatch.from_arrays([*(pa.array([t]).cast(k) for t, k in zip(tail[0], tail[2])), _binary_rows(tail[1][None, :])], names=[*keys, "body"])

    return work
