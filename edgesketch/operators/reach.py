"""Batched reachability over a component map."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def reachable(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """(pair_id, u, v, connected); null where an end is no vertex of the map."""
    met = pairs.join(labels.toDF("u", "cu"), "u", "left").join(labels.toDF("v", "cv"), "v", "left")
    return met.select("pair_id", "u", "v", (F.col("cu") == F.col("cv")).alias("connected"))


def hashed_pairs(spark, n: int, v_count: int, seed: int = 1) -> DataFrame:
    """n pairs of vertices by arithmetic that DuckDB repeats: uniform enough, and the same everywhere."""
    p = 2**31 - 1
    i = F.col("id") + 1
    u = ((i * 48271 + 7 * seed) % p * 16807 % p) % v_count
    v = ((i * 69621 + 13 * seed) % p * 48271 % p) % v_count
    return spark.range(n).select(F.col("id").alias("pair_id"), u.alias("u"), v.alias("v"))


def hashed_pairs_sql(n: int, v_count: str, seed: int = 1) -> str:
    p = 2**31 - 1
    return f"SELECT i AS pair_id, (((i + 1) * 48271 + {7 * seed}) % {p} * 16807 % {p}) % ({v_count}) AS u, (((i + 1) * 69621 + {13 * seed}) % {p} * 48271 % {p}) % ({v_count}) AS v FROM range({n}) t(i)"
