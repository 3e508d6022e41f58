"""Global connectivity from a sketch: contraction rounds, one sampler each.

In round r every live component xors its vertices' sampler r, decodes one crossing edge, and merges
along it. A component whose whole checksum is 0 is sealed; one that is not, but has no bucket of one
id, failed this round and tries the next sampler. Samplers that run out leave the result incomplete,
with the unresolved components listed; they never count as sealed.

Up to ``driver_limit`` vertices the component map is an array on the driver, broadcast to the scan
of a round, and the edges of a round (one per live component) meet a union-find there. Beyond it
labels are a table, joined by vertex, and edges are contracted by stars in the shared folder.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.functions.sampler import EDGE, EMPTY, FAILED, SamplerKernel
from edgesketch.operators.batching import body_words
from edgesketch.operators.sketch import GraphSketch, xor_bodies
from edgesketch.schemas import FOREST, endpoints_of
from edgesketch.tables import materialize, star_components

DRIVER_LIMIT = 1_000_000


@dataclass
class ForestResult:
    """A spanning forest, the component of each vertex, and whether every component is proven."""

    forest: DataFrame
    labels: DataFrame
    complete: bool
    rounds: int
    unresolved: list[int] = field(default_factory=list)
    stats: list[dict] = field(default_factory=list)


class UnionFind:
    """Least-root union-find over dense indices."""

    def __init__(self, n: int):
        self.parent = np.arange(n)

    def find(self, x: int) -> int:
        p = self.parent
        while p[x] != x:
            p[x] = p[p[x]]
            x = p[x]
        return int(x)

    def union(self, a: int, b: int) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        self.parent[max(a, b)] = min(a, b)
        return True

    def roots(self) -> np.ndarray:
        p = self.parent
        while True:
            q = p[p]
            if (q == p).all():
                return p.copy()
            p = self.parent = q


def vertices_of(sketch: GraphSketch, copy: int = 0) -> DataFrame:
    return sketch.sampler(copy, 0).select("vertex")


def spanning_forest(sketch: GraphSketch, vertices: DataFrame | None = None, seed_labels: DataFrame | None = None, sealed: DataFrame | None = None, copy: int = 0, driver_limit: int = DRIVER_LIMIT, remove: GraphSketch | None = None) -> ForestResult:
    """The forest of the sketched graph.

    ``vertices``: the vertex set, isolated ones included; else the seeds, or those of the sketch.
    ``seed_labels``: (vertex, component) pieces known to be connected. ``sealed``: components of these
    that are known to be whole. ``remove``: a sketch of that one copy, to xor in first.
    """
    base = seed_labels if seed_labels is not None else (vertices if vertices is not None else vertices_of(sketch, copy)).select("vertex", F.col("vertex").alias("component"))
    base = materialize(base.select(F.col("vertex").cast("long"), F.col("component").cast("long")).distinct(), "labels")
    n = base.count()
    if n <= driver_limit:
        return _on_driver(sketch, base, sealed, copy, remove)
    return _distributed(sketch, base, sealed, copy, remove)


def _bodies(sketch: GraphSketch, copy: int, r: int, remove: GraphSketch | None) -> DataFrame:
    rows = sketch.sampler(copy, r)
    return rows if remove is None else rows.unionByName(remove.sampler(0, r))


def _decoder(params):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = SamplerKernel(params)
        for batch in batches:
            if not batch.num_rows:
                continue
            body = body_words(batch.column("body"), params.words)
            status, eid = kernel.decode(body)
            yield pa.RecordBatch.from_arrays([batch.column("component"), pa.array(status.astype(np.int32)), pa.array(eid.view(np.int64)), pa.array(body[:, -1].view(np.int64))], names=["component", "status", "eid", "whole"])

    return work


DECODED = "component long, status int, eid long, whole long"


def _on_driver(sketch: GraphSketch, base: DataFrame, sealed: DataFrame | None, copy: int, remove: GraphSketch | None) -> ForestResult:
    spark, params = sketch.spark, sketch.params
    given = base.toArrow().sort_by("vertex")  # bounded by driver_limit
    vertex, named = given["vertex"].to_numpy(), given["component"].to_numpy()
    start = np.searchsorted(vertex, named)
    known = (start < len(vertex)) & (vertex[np.minimum(start, len(vertex) - 1)] == named) if len(vertex) else np.zeros(0, bool)
    if not known.all():
        raise ValueError("a seed component must be named by one of its vertices")
    uf = UnionFind(len(vertex))
    for i, j in zip(range(len(vertex)), start.tolist()):
        uf.union(i, j)
    whole_known: set[int] = set()
    if sealed is not None:
        names = np.array([r[0] for r in sealed.select("component").toLocalIterator()], np.int64)
        whole_known = {uf.find(int(i)) for i in np.searchsorted(vertex, names)}
    done = set(whole_known)
    forest: list[tuple[int, int, int]] = []
    stats, rounds, r = [], 0, 0
    failed: set[int] = set()
    while r < params.samplers:
        roots = uf.roots()
        live = set(np.unique(roots).tolist()) - done
        if not live:
            break
        rounds += 1
        flags = np.zeros(len(vertex), bool)
        flags[list(live)] = True
        told = spark.sparkContext.broadcast((vertex, roots, flags))
        decoded = _decode_round(_bodies(sketch, copy, r, remove), told, params).toArrow()
        told.unpersist()
        seen = np.searchsorted(vertex, decoded["component"].to_numpy())
        status, eid, whole = (decoded[c].to_numpy() for c in ("status", "eid", "whole"))
        checks = dict(zip(seen.tolist(), whole.tolist()))
        failed = set()
        done |= {c for c in live if checks.get(c, 0) == 0}  # no row, or a checksum of 0: no edge leaves it
        for c, s, e in zip(seen.tolist(), status.tolist(), eid.tolist()):
            if s == FAILED:
                failed.add(c)
            if s != EDGE:
                continue
            u, v = e >> 32, e & 0xFFFFFFFF
            ends = np.searchsorted(vertex, [u, v])
            if (ends >= len(vertex)).any() or vertex[ends[0]] != u or vertex[ends[1]] != v or (roots[ends[0]] == c) == (roots[ends[1]] == c):
                failed.add(c)  # a false positive: an edge of a cut has one end inside
                continue
            if uf.union(int(ends[0]), int(ends[1])):
                forest.append((u, v, r))
        stats.append({"round": r, "live": len(live), "edges": int((status == EDGE).sum()), "failed": len(failed)})
        # whole checksums are linear: those of merged components tell at once what is sealed
        merged: dict[int, int] = {}
        for c in live:
            root = uf.find(c)
            merged[root] = merged.get(root, 0) ^ checks.get(c, 0)
        touched = {uf.find(c) for c in whole_known}
        done = {uf.find(c) for c in done if uf.find(c) not in merged} | {c for c, x in merged.items() if x == 0 and c not in touched} | touched
        r += 1
    roots = uf.roots()
    open_ones = sorted(set(np.unique(roots).tolist()) - done) if len(vertex) else []
    labels = spark.createDataFrame(pa.table({"vertex": vertex, "component": vertex[roots]})) if len(vertex) else base
    made = spark.createDataFrame(pa.table([pa.array(c, t) for c, t in zip(zip(*forest), (pa.int64(), pa.int64(), pa.int32()))], names=["u", "v", "round"])) if forest else spark.createDataFrame([], FOREST)
    return ForestResult(made, labels, not open_ones, rounds, [int(vertex[i]) for i in open_ones], stats)


def _decode_round(bodies: DataFrame, told, params) -> DataFrame:
    """Bodies xored by live component and decoded; each vertex is its own component at first, without a shuffle."""

    def name(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vertex, roots, flags = told.value
        for batch in batches:
            at = np.searchsorted(vertex, batch.column("vertex").to_numpy())
            at = np.minimum(at, len(vertex) - 1)
            good = (vertex[at] == batch.column("vertex").to_numpy()) & flags[roots[at]]
            keep = pa.array(good)
            yield pa.RecordBatch.from_arrays([pa.array(vertex[roots[at[good]]]), batch.column("body").filter(keep)], names=["component", "body"])

    named = bodies.mapInArrow(name, "component long, body binary")
    return xor_bodies(named, ["component"]).mapInArrow(_decoder(params), DECODED)


def _distributed(sketch: GraphSketch, base: DataFrame, sealed: DataFrame | None, copy: int, remove: GraphSketch | None) -> ForestResult:
    """The same rounds with labels as a table; nothing that grows with the vertices comes to the driver."""
    params = sketch.params
    labels = base
    done = materialize(sealed.select("component").distinct() if sealed is not None else base.select("component").limit(0), "sealed")
    forest = None
    stats, rounds = [], 0
    for r in range(params.samplers):
        live = labels.join(done, "component", "left_anti")
        rounds += 1
        rows = _bodies(sketch, copy, r, remove).join(live, "vertex").select("component", "body")
        decoded = materialize(xor_bodies(rows, ["component"]).mapInArrow(_decoder(params), DECODED), "round")
        quiet = live.select("component").distinct().join(decoded.where(F.col("whole") != 0), "component", "left_anti")
        done = materialize(done.union(quiet).distinct(), "sealed")
        u, v = endpoints_of(F.col("eid"))
        found = decoded.where(F.col("status") == EDGE).select("component", u.alias("u"), v.alias("v"))
        ends = found.join(labels.toDF("u", "cu"), "u").join(labels.toDF("v", "cv"), "v")
        ends = materialize(ends.where((F.col("cu") != F.col("cv")) & ((F.col("cu") == F.col("component")) | (F.col("cv") == F.col("component")))), "crossing")
        n = ends.count()
        stats.append({"round": r, "edges": n})
        if n:
            # one edge from each component to a neighbour makes a forest but for 2-cycles and longer ones, which
            # picks by least edge id break: each component takes the least edge id offered to or by it
            both = ends.select(F.col("cu").alias("c"), "u", "v", "cu", "cv").union(ends.select("cv", "u", "v", "cu", "cv"))
            least = both.groupBy("c").agg(F.min(F.struct("u", "v", "cu", "cv")).alias("e")).select("e.*").distinct()
            least = materialize(least, "picked")
            forest = least.select("u", "v", F.lit(r).alias("round")) if forest is None else forest.union(least.select("u", "v", F.lit(r).alias("round")))
            stars, _ = star_components(least.select(F.col("cu").alias("u"), F.col("cv").alias("v")))
            names = stars.toDF("component", "root")
            labels = materialize(labels.join(names, "component", "left").select("vertex", F.coalesce("root", "component").alias("component")), "labels")
        if labels.join(done, "component", "left_anti").isEmpty():
            break
    least_names = labels.groupBy("component").agg(F.min("vertex").alias("least"))
    open_rows = labels.join(done, "component", "left_anti").select("component").distinct()
    unresolved = [r[0] for r in open_rows.limit(1000).collect()]
    final = labels.join(least_names, "component").select("vertex", F.col("least").alias("component"))
    made = forest if forest is not None else sketch.spark.createDataFrame([], FOREST)
    return ForestResult(made.select("u", "v", F.col("round").cast("int")), final, not unresolved, rounds, unresolved, stats)
