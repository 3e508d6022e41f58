"""Synthetic graphs by arithmetic that DuckDB repeats: Erdos-Renyi, Kronecker, matching, planted cuts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgesketch.functions.hashing import P31

#: Public initiator of the graph benchmark generator, in hundredths: chances of the four quadrants.
INITIATOR = (57, 19, 19, 5)


def _mixed(x: str, seed: int) -> str:
    """A number below 2**31 - 1 from an integer expression, in SQL of either dialect."""
    return f"(((({x}) % {P31}) * 48271 + {seed * 7919 + 12345}) % {P31} * 69621 % {P31} * 16807 % {P31})"


def erdos_renyi_sql(v: int, percent: int, seed: int, source: str) -> str:
    mix = _mixed(_mixed(f"a * {v} + b", seed), seed + 1)
    return f"SELECT a AS u, b AS v FROM (SELECT i // {v} AS a, i % {v} AS b FROM {source}) WHERE a < b AND {mix} % 100 < {percent}"


def erdos_renyi(spark: SparkSession, v: int, percent: int = 25, seed: int = 1) -> DataFrame:
    """Each pair is an edge with this chance."""
    spark.range(v * v).toDF("i").createOrReplaceTempView("edgesketch_pairs")
    return spark.sql(erdos_renyi_sql(v, percent, seed, "edgesketch_pairs").replace("i // ", "i div "))


def thinned_sql(pairs: str, percent: int, seed: int) -> str:
    mix = _mixed(_mixed("u * 1000003 + v", seed), seed + 1)
    return f"SELECT u, v FROM ({pairs}) WHERE {mix} % 100 < {percent}"


def thinned(spark: SparkSession, pairs: DataFrame, percent: int = 25, seed: int = 1) -> DataFrame:
    """G13 over given pairs: each is an edge with this chance."""
    pairs.createOrReplaceTempView("edgesketch_given")
    return spark.sql(thinned_sql("edgesketch_given", percent, seed))


def kronecker_sql(scale: int, draws: int, seed: int, source: str) -> str:
    a, b, c, _ = INITIATOR
    u, v = [], []
    for k in range(scale):
        r = f"({_mixed(_mixed(f'i * {scale} + {k}', seed), seed + 2)} % 100)"
        u.append(f"CASE WHEN {r} >= {a + b} THEN {1 << k} ELSE 0 END")
        v.append(f"CASE WHEN {r} >= {a} AND {r} < {a + b} OR {r} >= {a + b + c} THEN {1 << k} ELSE 0 END")
    return f"SELECT DISTINCT CAST(least(x, y) AS BIGINT) AS u, CAST(greatest(x, y) AS BIGINT) AS v FROM (SELECT {' + '.join(u)} AS x, {' + '.join(v)} AS y FROM {source}) WHERE x <> y"


def kronecker(spark: SparkSession, scale: int, draws: int, seed: int = 1, draws_of: DataFrame | None = None) -> DataFrame:
    """Each draw (of a range, or of the given numbers i) walks down ``scale`` quadrants; duplicates and loops go."""
    (spark.range(draws).toDF("i") if draws_of is None else draws_of).createOrReplaceTempView("edgesketch_draws")
    return spark.sql(kronecker_sql(scale, draws, seed, "edgesketch_draws"))


def matching(spark: SparkSession, v: int) -> DataFrame:
    """A perfect matching, the worst case of shipping every pending batch as a delta."""
    return spark.range(v // 2).select((F.col("id") * 2).alias("u"), (F.col("id") * 2 + 1).alias("v"))


def planted_cut(spark: SparkSession, side: int, across: int) -> DataFrame:
    """Two cliques of ``side`` vertices joined by ``across`` <= side edges."""
    ids = spark.range(side * side).select(F.floor(F.col("id") / side).alias("a"), (F.col("id") % side).alias("b")).where("a < b")
    both = ids.select(F.col("a").alias("u"), F.col("b").alias("v")).union(ids.select(F.col("a") + side, F.col("b") + side))
    return both.union(spark.range(across).select(F.col("id"), F.col("id") + side)).select(F.col("u").cast("long"), F.col("v").cast("long"))
