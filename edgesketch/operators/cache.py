"""The forest cache: the last answer's forest and labels, carried over later updates.

At a query the window since the cached answer is netted to the last change of each edge. Without a
deleted forest edge the surviving forest and the new edges answer it exactly, with no sketch. Else
their pieces seed the contraction, and only pieces of broken components are queried. Without a cached
answer the sketch is contracted from its vertices.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.operators.forest import ForestResult, spanning_forest
from edgesketch.operators.reach import reachable
from edgesketch.operators.sketch import GraphSketch
from edgesketch.schemas import FOREST
from edgesketch.sources.updates import canonical
from edgesketch.tables import materialize, star_components


class ForestCache:
    """Holds one answer and absorbs the updates after it."""

    def __init__(self, vertices: DataFrame, result: ForestResult | None = None, at_seq: int | None = None):
        self.vertices, self.result, self.at_seq = vertices.select("vertex").distinct(), result, at_seq
        self.state = "cold" if result is None else "exact"
        self.last_state = None

    def _net(self, window: DataFrame) -> tuple[DataFrame, DataFrame]:
        last = canonical(window).groupBy("u", "v").agg(F.max_by("delta", "seq").alias("d"))
        last = materialize(last, "window")
        return last.where("d > 0").select("u", "v"), last.where("d < 0").select("u", "v")

    def pieces(self, window: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
        """(pieces, kept forest edges, broken old components) after a window of updates."""
        born, dead = self._net(window)
        forest = self.result.forest.select("u", "v")
        kept = forest.join(dead, ["u", "v"], "left_anti")
        broken = forest.join(dead, ["u", "v"], "left_semi").join(self.result.labels.toDF("u", "component"), "u").select("component").distinct()
        tied = kept.select("u", "v").union(born)
        stars, _ = star_components(tied)
        pieces = self.vertices.join(stars, "vertex", "left").select("vertex", F.coalesce("component", "vertex").alias("component"))
        return materialize(pieces, "pieces"), tied, materialize(broken, "broken")

    def query(self, sketch_at, window: DataFrame | None, at_seq: int) -> ForestResult:
        """The answer at ``at_seq``. ``sketch_at()`` gives the sketch as of then, and is called only if it is needed."""
        if self.result is None:
            self.last_state, self.result = "cold", spanning_forest(sketch_at(), vertices=self.vertices)
        else:
            pieces, tied, broken = self.pieces(window)
            if broken.isEmpty():
                self.last_state = "exact"
                # the kept forest and the born edges span every piece; an edge that joins no two pieces of it is dropped
                spanning = tied.select("u", "v", F.lit(-1).alias("round"))
                self.result = ForestResult(_thin(spanning), pieces, True, 0)
            else:
                self.last_state = "seeded"
                old = self.result.labels.toDF("vertex", "was")
                live = pieces.join(old, "vertex").join(broken.toDF("was"), "was", "left_semi").select("component").distinct()
                whole = pieces.select("component").distinct().join(live, "component", "left_anti")
                found = spanning_forest(sketch_at(), seed_labels=pieces, sealed=whole)
                both = _thin(tied.select("u", "v", F.lit(-1).alias("round"))).unionByName(found.forest)
                self.result = ForestResult(both, found.labels, found.complete, found.rounds, found.unresolved, found.stats)
        self.at_seq, self.state = at_seq, "exact"
        return self.result

    def reachable(self, pairs: DataFrame, window: DataFrame, sketch_at, at_seq: int) -> DataFrame:
        """Pairs answered from the pieces alone when none of the touched components is broken."""
        if self.result is not None:
            pieces, _, broken = self.pieces(window)
            ends = pairs.select(F.explode(F.array("u", "v")).alias("vertex")).distinct()
            touched = ends.join(pieces, "vertex").select("component").distinct().join(pieces, "component").select("vertex")
            hurt = touched.join(self.result.labels, "vertex").join(broken, "component", "left_semi")
            if hurt.isEmpty():
                self.last_state = "exact"
                return reachable(pairs, pieces)
        return reachable(pairs, self.query(sketch_at, window, at_seq).labels)


def _thin(edges: DataFrame) -> DataFrame:
    """A spanning forest of few edges: a union-find over them where they are few, else rounds of stars."""
    spark = edges.sparkSession
    edges = materialize(edges, "thin")
    if edges.count() > 2_000_000:
        return boruvka(edges.select("u", "v"))
    rows = edges.toArrow()  # bounded by the count above
    parent: dict[int, int] = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    keep = []
    for u, v, r in zip(*(rows[k].to_pylist() for k in ("u", "v", "round"))):
        a, b = find(u), find(v)
        if a != b:
            parent[max(a, b)] = min(a, b)
            keep.append((u, v, r))
    if not keep:
        return spark.createDataFrame([], FOREST)
    return spark.createDataFrame(pa.table([pa.array(c, t) for c, t in zip(zip(*keep), (pa.int64(), pa.int64(), pa.int32()))], names=["u", "v", "round"]))


def boruvka(edges: DataFrame) -> DataFrame:
    """A spanning forest of real edges by rounds: each component takes its least edge."""
    spark = edges.sparkSession
    left, forest, r = materialize(canonical(edges).distinct().select("u", "v", F.col("u").alias("cu"), F.col("v").alias("cv")), "edges"), None, 0
    while not left.isEmpty():
        both = left.select(F.col("cu").alias("c"), "u", "v", "cu", "cv").union(left.select("cv", "u", "v", "cu", "cv"))
        picked = materialize(both.groupBy("c").agg(F.min(F.struct("u", "v", "cu", "cv")).alias("e")).select("e.*").distinct(), "picked")
        step = picked.select("u", "v", F.lit(r).alias("round"))
        forest = step if forest is None else forest.union(step)
        stars, _ = star_components(picked.select(F.col("cu").alias("u"), F.col("cv").alias("v")))
        a, b = stars.toDF("cu", "ru"), stars.toDF("cv", "rv")
        moved = left.join(a, "cu", "left").join(b, "cv", "left").select("u", "v", F.coalesce("ru", "cu").alias("cu"), F.coalesce("rv", "cv").alias("cv"))
        left, r = materialize(moved.where("cu <> cv"), "edges"), r + 1
    return forest if forest is not None else spark.createDataFrame([], FOREST)
