"""Exact and lossless baselines: acquisition, scatter, adjacency, components, cuts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.operators.cuts import crossing
from edgesketch.sources.updates import canonical, live_edges, parity_edges
from edgesketch.tables import materialize, parts, star_components


def acquire(updates: DataFrame) -> None:
    """B1: reads the whole stream and drops it: the cost that no system avoids."""
    updates.write.format("noop").mode("overwrite").save()


def scatter(updates: DataFrame) -> None:
    """B2: sends every update to a random place."""
    updates.repartition(parts(updates.sparkSession), F.xxhash64("seq", "u", "v")).write.format("noop").mode("overwrite").save()


def adjacency_bits(updates: DataFrame, v_count: int) -> DataFrame:
    """A bit matrix by parity: (u, word, bits), one bit flip for each update and end."""
    rows = canonical(updates.select("u", "v"))
    both = rows.select("u", "v").union(rows.select("v", "u"))
    flip = F.expr("shiftleft(1L, cast(v % 64 as int))")
    return both.groupBy("u", F.floor(F.col("v") / 64).alias("word")).agg(F.bit_xor(flip).alias("bits")).where("bits <> 0")


def adjacency_list(updates: DataFrame) -> DataFrame:
    """(vertex, near, degree)."""
    rows = live_edges(updates)
    both = rows.select(F.col("u").alias("vertex"), F.col("v").alias("x")).union(rows.select("v", "u"))
    return both.groupBy("vertex").agg(F.array_sort(F.collect_list("x")).alias("near")).withColumn("degree", F.size("near"))


def components(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """(vertex, component) by star contraction; isolated vertices too if ``vertices`` is given."""
    stars, _ = star_components(edges)
    if vertices is None:
        return stars
    return vertices.select("vertex").distinct().join(stars, "vertex", "left").select("vertex", F.coalesce("component", "vertex").alias("component"))


def label_propagation(edges: DataFrame, most_rounds: int = 1000) -> tuple[DataFrame, int]:
    """Least labels sent along every edge until nothing changes; as many rounds as the diameter."""
    rows = canonical(edges).distinct()
    both = materialize(rows.select("u", "v").union(rows.select("v", "u")), "both")
    now = materialize(both.select(F.col("u").alias("vertex")).distinct().withColumn("component", F.col("vertex")), "labels")
    for k in range(1, most_rounds + 1):
        heard = both.join(now, F.col("u") == F.col("vertex")).groupBy("v").agg(F.min("component").alias("m"))
        new = materialize(now.join(heard, F.col("vertex") == F.col("v"), "left").select("vertex", F.least("component", F.coalesce("m", "component")).alias("component"), (F.col("m") < F.col("component")).alias("moved")), "labels")
        done = new.where("moved").isEmpty()
        now = new.drop("moved")
        if done:
            return now, k
    raise RuntimeError("labels did not settle")


def batch_dynamic(updates: DataFrame, batch_rows: int) -> DataFrame:
    """Batches of inserts only or deletes only; exact components after the last.

    A stretch of the sequence of at most ``batch_rows`` updates is netted to the last change of each
    edge and parted by sign: its deletes are a batch, after which labels are made anew from the live
    edges that are left, and its inserts another, which keeps the labels and only ties them.
    """
    first, last = updates.agg(F.min("seq"), F.max("seq")).first()
    if first is None:
        return updates.select(F.col("u").alias("vertex"), F.col("v").alias("component")).limit(0)
    n = updates.count()
    step = max(1, -(-(last - first + 1) * batch_rows // max(1, n)))
    labels, vertices = None, updates.select(F.explode(F.array("u", "v")).alias("vertex")).distinct()
    at = first
    while at <= last:
        stretch = updates.where((F.col("seq") >= at) & (F.col("seq") < at + step))
        net = materialize(canonical(stretch).groupBy("u", "v").agg(F.max_by("delta", "seq").alias("d")), "net")
        dead, born = net.where("d < 0").select("u", "v"), net.where("d > 0").select("u", "v")
        if labels is not None and not dead.isEmpty():
            labels = materialize(components(live_edges(updates, at - 1).join(dead, ["u", "v"], "left_anti")), "labels")
        tied = born if labels is None else born.union(labels.where("vertex <> component").select("vertex", "component"))
        labels = materialize(components(tied), "labels")
        at += step
    return vertices.join(labels, "vertex", "left").select("vertex", F.coalesce("component", "vertex").alias("component"))


def recompute(updates: DataFrame, upto: int | None = None) -> DataFrame:
    """Net edges and components from scratch."""
    return components(live_edges(updates, upto))


def min_cut(updates: DataFrame, vertices: DataFrame) -> int:
    """The global minimum cut over all live edges, on the driver; raises beyond what it searches."""
    from edgesketch.operators.cuts import MIN_CUT_VERTICES, least_cut

    edges, named = materialize(parity_edges(updates), "live"), vertices.select("vertex").distinct()
    if named.count() > MIN_CUT_VERTICES or edges.count() > 2_000_000:
        raise ValueError("an exact minimum cut is not searched in so large a graph")
    return least_cut(((r.u, r.v) for r in edges.toLocalIterator()), [r.vertex for r in named.toLocalIterator()])


def cut_values(updates: DataFrame, cuts: DataFrame) -> DataFrame:
    """(cut_id, n) over all live edges."""
    return crossing(parity_edges(updates), cuts)
