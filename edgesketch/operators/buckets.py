"""Layout A: one row for each non-empty bucket, made by Catalyst expressions alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from edgesketch.functions.hashing import P31, pair31_factors, pair31_sql, trailing_zeros_sql
from edgesketch.functions.sampler import SketchParams
from edgesketch.schemas import endpoints_of
from edgesketch.sources.updates import endpoints

WHOLE = -1
#: Indices of the pair31 hashes: the checksum's, and the first of the columns'.
CHECK_INDEX, FIRST_INDEX = 0, 1


def _slots(params: SketchParams) -> Column:
    """A literal array of all (copy, sampler, column) with the factors of their hash."""
    made = []
    for copy in range(params.copies):
        for s in range(params.samplers):
            for c in range(params.columns):
                i = FIRST_INDEX + params.seed + (copy * params.samplers + s) * params.columns + c
                a, b, d = pair31_factors(i)
                made.append(F.struct(F.lit(copy).alias("copy"), F.lit(s).alias("sampler"), F.lit(c).alias("col"), F.lit(i).cast("long").alias("seed"), *(F.lit(x).cast("long").alias(n) for x, n in ((a, "a"), (b, "b"), (d, "c")))))
    return F.array(*made)


def check_of(eid: Column, params: SketchParams) -> Column:
    """The checksum of an id in SQL: never 0 for pair31, 64 bits for xxhash64."""
    if params.hash_family == "pair31":
        lo, hi = endpoints_of(eid)
        a, b, c = (F.lit(x).cast("long") for x in pair31_factors(CHECK_INDEX + params.seed))
        return pair31_sql(lo, hi, a, b, c) + 1
    return F.xxhash64(F.lit(params.seed), eid)


def toggles(updates: DataFrame, params: SketchParams) -> DataFrame:
    """(copy, vertex, sampler, col, level, xe, xc) of all buckets that are not empty.

    The level of an id is its hash's trailing zeros; a nested sampler takes the suffix xor by
    exploding the levels up to it. Partial aggregation xors before the shuffle.
    """
    rows = endpoints(updates).select("vertex", "eid", check_of(F.col("eid"), params).alias("chk"))
    # equal ids of a vertex cancel in pairs before they are spread over the slots
    rows = rows.groupBy("vertex", "eid", "chk").agg((F.count(F.lit(1)) % 2).alias("odd")).where("odd = 1").drop("odd")
    spread = rows.select("vertex", "eid", "chk", F.explode(_slots(params)).alias("s")).select("vertex", "eid", "chk", "s.*")
    if params.hash_family == "pair31":
        lo, hi = endpoints_of(F.col("eid"))
        h = pair31_sql(lo, hi, F.col("a"), F.col("b"), F.col("c"))
    else:
        h = F.xxhash64("seed", "eid")
    level = F.when(h == 0, F.lit(params.levels - 1)).otherwise(F.least(trailing_zeros_sql(h), F.lit(params.levels - 1)))
    levels = F.explode(F.sequence(F.lit(0), level)) if params.variant == "nested" else level
    spread = spread.select("copy", "vertex", "sampler", "col", levels.alias("level"), "eid", "chk").withColumn("level", F.col("level").cast("int"))
    buckets = spread.groupBy("copy", "vertex", "sampler", "col", "level").agg(F.bit_xor("eid").alias("xe"), F.bit_xor("chk").alias("xc"))
    whole = rows.groupBy("vertex").agg(F.bit_xor("eid").alias("xe"), F.bit_xor("chk").alias("xc"))
    each = F.explode(F.array(*(F.struct(F.lit(c).alias("copy"), F.lit(s).alias("sampler")) for c in range(params.copies) for s in range(params.samplers))))
    whole = whole.select(each.alias("k"), "vertex", "xe", "xc").select("k.copy", "vertex", "k.sampler", F.lit(0).alias("col"), F.lit(WHOLE).alias("level"), "xe", "xc")
    return buckets.unionByName(whole).where("xe <> 0 OR xc <> 0")


def decode(buckets: DataFrame, params: SketchParams) -> DataFrame:
    """(copy, vertex, sampler, status, eid): a bucket of one id, the sparsest level first; else empty or failed."""
    lo, hi = endpoints_of(F.col("xe"))
    good = (F.col("level") >= 0) & (F.col("xe") != 0) & (lo < hi) & (hi < params.v_count) & (check_of(F.col("xe"), params) == F.col("xc"))
    rank = F.struct(-F.col("level"), F.col("col"))
    found = buckets.groupBy("copy", "vertex", "sampler").agg(
        F.max(F.when(F.col("level") == WHOLE, F.col("xc"))).alias("whole"), F.min_by(F.when(good, F.col("xe")), F.when(good, rank)).alias("eid")
    )
    status = F.when(F.col("whole").isNull(), "empty").when(F.col("eid").isNotNull(), "edge").otherwise("failed")
    return found.select("copy", "vertex", "sampler", status.alias("status"), F.when(F.col("whole").isNotNull(), F.col("eid")).alias("eid"))


def handshake(buckets: DataFrame) -> DataFrame:
    """The xor over all vertices of every bucket: always 0, as each edge has two ends."""
    over = buckets.groupBy("copy", "sampler", "col", "level").agg(F.bit_xor("xe").alias("xe"), F.bit_xor("xc").alias("xc"))
    return over.agg(F.bit_or("xe").alias("ids"), F.bit_or("xc").alias("checks"))


def pair31_oracle(edges_sql: str, params: SketchParams, nested: bool = False) -> str:
    """The bucket rows of layout A in DuckDB, by the same arithmetic."""
    slots = ", ".join(f"({s}, {c}, {', '.join(f'{x}::BIGINT' for x in pair31_factors(FIRST_INDEX + params.seed + s * params.columns + c))})" for s in range(params.samplers) for c in range(params.columns))
    a, b, d = pair31_factors(CHECK_INDEX + params.seed)
    level = "lvl" if not nested else "unnest(range(0, lvl + 1))"
    return f"""
WITH g AS ({edges_sql}), ep AS (SELECT u AS vertex, u, v FROM g UNION ALL SELECT v, u, v FROM g),
e AS (SELECT vertex, (u << 32) | v AS eid, u, v, (({a} * u) % {P31} + ({b} * v) % {P31} + {d}) % {P31} + 1 AS chk FROM ep),
slots(sampler, col, a, b, c) AS (VALUES {slots}),
h AS (SELECT vertex, eid, chk, sampler, col, ((a * u) % {P31} + (b * v) % {P31} + c) % {P31} AS h FROM e, slots),
l AS (SELECT vertex, eid, chk, sampler, col, CASE WHEN h = 0 THEN {params.levels - 1} ELSE least(bit_count((h & -h) - 1), {params.levels - 1}) END AS lvl FROM h),
m AS (SELECT vertex, eid, chk, sampler, col, {level} AS level FROM l),
k AS (SELECT vertex, sampler, col, level, bit_xor(eid) AS xe, bit_xor(chk) AS xc FROM m GROUP BY ALL
      UNION ALL SELECT vertex, sampler, 0, -1, bit_xor(eid), bit_xor(chk) FROM e, (SELECT DISTINCT sampler FROM slots) GROUP BY ALL)
SELECT vertex, sampler::INTEGER AS sampler, col::INTEGER AS col, level::INTEGER AS level, xe, xc FROM k WHERE xe <> 0 OR xc <> 0"""
