"""Files of updates: text formats, the packed 9-byte log, and a Python data source of synthetic graphs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

_PACKED = np.dtype([("u", "<u4"), ("v", "<u4"), ("delta", "i1")])
#: Updates in one row of a packed log.
PACKED_ROWS = 1 << 16


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", **options) -> DataFrame:
    """(u, v) from csv, json, orc, parquet or white-space separated text."""
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        rows = spark.read.text(path).where(~F.col("value").startswith("#"))
        return rows.select(parts[0].cast("long").alias("u"), parts[1].cast("long").alias("v"))
    return spark.read.format(fmt).options(**options).schema("u long, v long").load(path)


def write_packed(updates: DataFrame, path: str) -> None:
    """The log as 9 bytes an update, in stretches of a bounded size: (first_seq, n, body), in seq order."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, PACKED_ROWS):
                batch = whole.slice(at, PACKED_ROWS)
                body = np.zeros(batch.num_rows, _PACKED)
                for k in ("u", "v", "delta"):
                    body[k] = batch.column(k).to_numpy()
                seq = batch.column("seq").to_numpy()
                yield pa.RecordBatch.from_arrays([pa.array(seq[:1]), pa.array([len(body)], pa.int32()), pa.array([seq.tobytes()], pa.binary()), pa.array([body.tobytes()], pa.binary())], names=["first_seq", "n", "seqs", "body"])

    dealt = updates.select("seq", "u", "v", "delta").repartitionByRange("seq").sortWithinPartitions("seq")
    dealt.mapInArrow(pack, "first_seq long, n int, seqs binary, body binary").write.mode("overwrite").parquet(path)


def read_packed(spark: SparkSession, path: str) -> DataFrame:
    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for seqs, cell in zip(batch.column("seqs").to_pylist(), batch.column("body").to_pylist()):
                body = np.frombuffer(cell, _PACKED)
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(seqs, np.int64)), pa.array(body["u"].astype(np.int64)), pa.array(body["v"].astype(np.int64)), pa.array(body["delta"].copy())], names=["seq", "u", "v", "delta"])

    return spark.read.parquet(path).mapInArrow(unpack, "seq long, u long, v long, delta tinyint")


class SyntheticGraph(DataSource):
    """``spark.read.format("edgesketch_graph")``: a random graph of ``vertices`` and ``percent``, by rows of the matrix."""

    @classmethod
    def name(cls) -> str:
        return "edgesketch_graph"

    def schema(self) -> str:
        return "u long, v long"

    def reader(self, schema) -> DataSourceReader:
        return _GraphReader(int(self.options.get("vertices", 64)), int(self.options.get("percent", 25)), int(self.options.get("seed", 1)), int(self.options.get("tasks", 8)))


class _GraphReader(DataSourceReader):
    def __init__(self, v: int, percent: int, seed: int, tasks: int):
        self.v, self.percent, self.seed, self.tasks = v, percent, seed, tasks

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.tasks)]

    def read(self, partition: InputPartition):
        from edgesketch.functions.hashing import mix64

        for u in range(partition.value, self.v, self.tasks):
            v = np.arange(u + 1, self.v, dtype=np.uint64)
            keep = v[mix64(np.uint64(u << 32) | v, self.seed) % np.uint64(100) < self.percent].astype(np.int64)
            if len(keep):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keep), u, np.int64)), pa.array(keep)], names=["u", "v"])
