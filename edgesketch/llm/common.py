"""Session helpers shared by the operators."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from edgesketch.tables import delete_path, materialize, scratch_path, scratch_scope, shared_dir, shuffles_released, table

__all__ = ["Sieve", "ascii_lower", "delete_path", "materialize", "partitions_for", "scratch_path", "scratch_scope", "shared_dir", "shuffles_released", "table", "text_slices"]


def text_slices(batch: pa.RecordBatch, column: str, most_bytes: int = 2 << 20):
    """Cuts a batch into row ranges of about ``most_bytes`` of text; a longer text stands alone."""
    lengths = batch.column(column).cast(pa.large_string()).fill_null("")
    import numpy as np
    import pyarrow.compute as pc

    sizes = pc.binary_length(lengths).to_numpy(zero_copy_only=False).astype(np.int64)
    at, n = 0, len(sizes)
    ends = np.cumsum(sizes)
    while at < n:
        base = ends[at] - sizes[at]
        stop = max(at + 1, int(np.searchsorted(ends, base + most_bytes, side="right")))
        yield batch.slice(at, stop - at)
        at = stop


def ascii_lower(column):
    """Lower-cases A-Z and nothing else."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.translate(column, upper, upper.lower())


def partitions_for(spark: SparkSession) -> int:
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)


#: Most bits of a sieve: a broadcast table of half a million rows of two numbers.
SIEVE_BITS = 1 << 25


class Sieve:
    """Which rows may have one of the given keys, told where the rows lie: a row without is surely none, one with may be.

    What may be still goes to an exact join; the rest, as a rule nearly all of a large table, is not shuffled for it.
    A key sets two bits, of 16 to 32 a key until ``most_bits`` are taken; beyond that more rows pass and none is lost.
    """

    def __init__(self, keys: DataFrame, column: str, most_bits: int = SIEVE_BITS):
        self.bits = min(most_bits, 1 << max(10, (16 * keys.count()).bit_length()))
        word, mask = self._place(column)
        self.words = materialize(keys.select(word.alias("__es_word"), mask.alias("mask")).groupBy("__es_word").agg(F.bit_or("mask").alias("__es_mask")), "sieve")

    def _place(self, column: str):
        h, one = F.xxhash64(F.col(column)), F.lit(1).cast("long")
        low, high = (F.call_function("shiftleft", one, x.bitwiseAND(F.lit(63)).cast("int")) for x in (h, F.shiftrightunsigned(h, 58)))
        return F.shiftright(h.bitwiseAND(F.lit(self.bits - 1)), 6), low.bitwiseOR(high)

    def _met(self, rows: DataFrame, column: str, how: str) -> DataFrame:
        word, mask = self._place(column)
        return rows.join(F.broadcast(self.words), (word == F.col("__es_word")) & (mask.bitwiseAND(F.col("__es_mask")) == mask), how)

    def may_have(self, rows: DataFrame, column: str, anyway: Column | None = None) -> DataFrame:
        """The rows that may have a key, and those that ``anyway`` is true of."""
        if anyway is None:
            return self._met(rows, column, "left_semi")
        return self._met(rows, column, "left").where(anyway | F.col("__es_word").isNotNull()).select(*rows.columns)

    def surely_without(self, rows: DataFrame, column: str) -> DataFrame:
        return self._met(rows, column, "left_anti")
