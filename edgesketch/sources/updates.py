"""Edge update streams: making, validating and netting them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from edgesketch.schemas import edge_id
from edgesketch.tables import materialize


def _no_time() -> Column:
    return F.lit(None).cast("timestamp").alias("ts")



def canonical(edges: DataFrame) -> DataFrame:
    """u < v, without self loops and nulls."""
    good = edges.where(F.col("u").isNotNull() & F.col("v").isNotNull() & (F.col("u") != F.col("v")))
    return good.withColumns({"u": F.least("u", "v").cast("long"), "v": F.greatest("u", "v").cast("long")})


def _numbered(df: DataFrame, *order: Column) -> DataFrame:
    """A dense sequence number by range partitions: counts per partition, then offsets, no single task.

    The partitions are written before they are counted: a second evaluation may draw other bounds, and
    adaptive execution may join its narrower partitions differently.
    """
    dealt = df.repartitionByRange(*order).sortWithinPartitions(*order)
    marked = materialize(dealt.withColumn("_m", F.monotonically_increasing_id()), "numbered")
    marked = marked.withColumns({"_p": F.shiftright("_m", 33), "_k": F.col("_m").bitwiseAND((1 << 33) - 1)})
    sizes = marked.groupBy("_p").agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.withColumn("_b", F.coalesce(F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return marked.join(F.broadcast(before.select("_p", "_b")), "_p").withColumn("seq", (F.col("_b") + F.col("_k")).cast("long")).drop("_m", "_p", "_k", "_b")


def simple(edges: DataFrame) -> bool:
    """Whether all edges have u < v: distinct ones then need not be told apart again."""
    return edges.where("u IS NULL OR v IS NULL OR u >= v").isEmpty()


def from_edges(edges: DataFrame, distinct: bool = False) -> DataFrame:
    """Each distinct edge inserted once, in order of its ends; ``distinct``: the rows are so already, with u < v."""
    once = canonical(edges.select("u", "v"))
    once = once if distinct else once.distinct()
    return once.select(edge_id(F.col("u"), F.col("v")).alias("seq"), "u", "v", F.lit(1).cast("tinyint").alias("delta"), _no_time())


def toggle(occurrences: DataFrame, *order: str) -> DataFrame:
    """Odd occurrences of an edge insert it, even ones delete it; ``order`` sorts occurrences."""
    rows = canonical(occurrences)
    nth = F.row_number().over(Window.partitionBy("u", "v").orderBy(*order))
    made = rows.withColumn("delta", F.when(nth % 2 == 1, 1).otherwise(-1).cast("tinyint"))
    return made.select(F.col(order[0]).cast("long").alias("seq"), "u", "v", "delta", _no_time())


def churn(edges: DataFrame, repeats: int = 7, seed: int = 1) -> DataFrame:
    """S3: each edge inserted ``repeats`` times and deleted once less, alternating, slots hash-shuffled."""
    once = canonical(edges.select("u", "v")).distinct()
    slots = 2 * repeats - 1
    # the k-th slot of an edge lies in the k-th stretch of the sequence, shuffled within it
    made = once.select("u", "v", F.explode(F.sequence(F.lit(0), F.lit(slots - 1))).alias("k"))
    spot = F.pmod(F.xxhash64(F.lit(seed), "u", "v", "k"), F.lit(1 << 40))
    return made.select((F.col("k").cast("long") * F.lit(1 << 40) + spot).alias("seq"), "u", "v", F.when(F.col("k") % 2 == 0, 1).otherwise(-1).cast("tinyint").alias("delta"), _no_time())


def returns(occurrences: DataFrame) -> DataFrame:
    """(u, v, day, back) rows; those marked back are undone 30 days later, on net changes 0-1 only."""
    rows = canonical(occurrences)
    put = rows.select("u", "v", F.col("day").alias("t"), F.lit(1).alias("d"))
    gone = rows.where("back").select("u", "v", (F.col("day") + 30).alias("t"), F.lit(-1).alias("d"))
    steps = put.union(gone).groupBy("u", "v", "t").agg(F.sum("d").alias("d"))
    upto = Window.partitionBy("u", "v").orderBy("t").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    held = steps.withColumn("n", F.sum("d").over(upto)).withColumn("was", F.col("n") - F.col("d"))
    moved = held.where((F.col("n") > 0) != (F.col("was") > 0))
    return moved.select(F.col("t").cast("long").alias("seq"), "u", "v", F.when(F.col("n") > 0, 1).otherwise(-1).cast("tinyint").alias("delta"), _no_time())


def expiring(events: DataFrame, days: int = 7) -> DataFrame:
    """(u, v, ts) rows; an edge goes ``days`` days after its last event of a run."""
    rows = canonical(events)
    w = Window.partitionBy("u", "v").orderBy("ts")
    gap = F.expr(f"INTERVAL {days} DAYS")
    steps = rows.withColumn("before", F.lag("ts").over(w)).withColumn("after", F.lead("ts").over(w))
    put = steps.where(F.col("before").isNull() | (F.col("ts") > F.col("before") + gap)).select("u", "v", "ts", F.lit(1).alias("delta"))
    gone = steps.where(F.col("after").isNull() | (F.col("after") > F.col("ts") + gap)).select("u", "v", (F.col("ts") + gap).alias("ts"), F.lit(-1).alias("delta"))
    both = put.union(gone)
    return both.select(F.unix_micros(F.col("ts").cast("timestamp")).alias("seq"), "u", "v", F.col("delta").cast("tinyint").alias("delta"), F.col("ts").cast("timestamp").alias("ts"))


def endpoints(updates: DataFrame) -> DataFrame:
    """M3: (vertex, eid) twice for each update; narrow."""
    rows = canonical(updates.select("u", "v"))
    return rows.select(F.explode(F.array("u", "v")).alias("vertex"), edge_id(F.col("u"), F.col("v")).alias("eid"))


def live_edges(updates: DataFrame, upto: int | None = None) -> DataFrame:
    """M2: the edges of a prefix of the stream; sums are pre-aggregated before the shuffle."""
    rows = updates if upto is None else updates.where(F.col("seq") <= upto)
    return canonical(rows.select("u", "v", "delta")).groupBy("u", "v").agg(F.sum("delta").alias("n")).where("n = 1").select("u", "v")


def parity_edges(updates: DataFrame) -> DataFrame:
    """The edges with an odd number of updates: what an xor sketch sees."""
    return canonical(updates.select("u", "v")).groupBy("u", "v").agg((F.count(F.lit(1)) % 2).alias("n")).where("n = 1").select("u", "v")


def validate(updates: DataFrame) -> DataFrame:
    """M1: the updates that insert a present edge or delete an absent one."""
    rows = canonical(updates)
    before = F.coalesce(F.lag("delta").over(Window.partitionBy("u", "v").orderBy("seq", "delta")), F.lit(-1))
    return rows.withColumn("_b", before).where(F.col("_b") == F.col("delta")).drop("_b")


def number(updates: DataFrame, *order: str) -> DataFrame:
    """A stream with dense sequence numbers in the given order."""
    return _numbered(updates.drop("seq"), *[F.col(c) for c in order])
