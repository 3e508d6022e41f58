"""Streaming ingestion into epochs of a sketch, a stateful gather buffer, and replay with queries between."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgesketch.functions.sampler import SketchParams
from edgesketch.operators import certificate, cuts
from edgesketch.operators.batching import BatchPolicy, sketched_rows
from edgesketch.operators.cache import ForestCache
from edgesketch.operators.sketch import GraphSketch, read_bodies, write_bodies, xor_bodies
from edgesketch.sources.updates import endpoints, live_edges
from edgesketch.tables import materialize

QUERY_KINDS = ("global", "pairs", "kconn", "cut")


def batch_path(path: str, batch_id: int) -> str:
    return f"{path}/batch={batch_id:012d}"


def ingest(stream: DataFrame, path: str, params: SketchParams, checkpoint: str, policy: BatchPolicy = BatchPolicy(), trigger: dict | None = None):
    """Starts a query that sketches each micro-batch into a folder named after its batch id.

    Xor is not idempotent: a batch that is delivered again overwrites its own folder, so nothing
    cancels. The sketch is the xor of all folders.
    """

    def sink(batch: DataFrame, batch_id: int) -> None:
        rows = sketched_rows(endpoints(batch), params, policy)
        write_bodies(rows, params, batch_path(path, batch_id), "overwrite")

    return stream.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def sketched(spark: SparkSession, path: str, params: SketchParams, out: str, upto: int | None = None) -> GraphSketch:
    """The sketch of all batches so far, or of those up to a batch id."""
    rows = read_bodies(spark, params, path, ", batch long")
    if upto is not None:
        rows = rows.where(F.col("batch") <= upto)
    return GraphSketch._write(spark, xor_bodies(rows.select("vertex", "body"), ["vertex"]), params, out, upto or 0)


def gather(stream: DataFrame, params: SketchParams, groups: int = 64, alpha: float = 1.0, idle: str | None = None) -> DataFrame:
    """M8 as a stateful operator: holds ids by group of vertices until a vertex has a full batch.

    Emits (vertex, eids) batches; the group, not the vertex, is the key, so keys stay few. What stays
    pending is in the state store. Needs the RocksDB provider.
    """
    import pandas as pd
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    full = params.capacity(alpha)

    class Gather(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.pending = handle.getMapState("pending", "vertex long", "eids array<long>")

        def handleInputRows(self, key, rows, timerValues):
            for part in rows:
                for vertex, own in part.groupby("vertex"):
                    had = list(self.pending.getValue((int(vertex),))[0]) if self.pending.containsKey((int(vertex),)) else []
                    had += [int(x) for x in own["eid"]]
                    while len(had) >= full:
                        yield pd.DataFrame({"vertex": [int(vertex)], "eids": [had[:full]]})
                        had = had[full:]
                    if had:
                        self.pending.updateValue((int(vertex),), (had,))
                    else:
                        self.pending.removeKey((int(vertex),))

        def close(self) -> None:
            pass

    ends = endpoints(stream).withColumn("g", F.pmod(F.xxhash64("vertex"), F.lit(groups)))
    return ends.groupBy("g").transformWithStateInPandas(Gather(), "vertex long, eids array<long>", "Append", "None")


def replay(updates: DataFrame, query_points: list[tuple[int, int, str]], params: SketchParams, vertices: DataFrame, policy: BatchPolicy = BatchPolicy(), cached: bool = True, pairs: DataFrame | None = None, told: Callable[[int, object], None] | None = None, cut_rows: DataFrame | None = None) -> list[tuple[int, str, object]]:
    """Queries between updates, each over the committed prefix: (query_id, state, result) in order.

    ``query_points``: (query_id, at_seq, kind). A kind is ``global`` (a forest), ``pairs`` (reachability of
    ``pairs``), ``kconn`` (a certificate of as many forests as the sketch has copies) or ``cut`` (the values
    of ``cut_rows`` in such a certificate). The sketch advances only when an answer needs it; the forest
    cache answers the rest of a burst, and a certificate holds until an update follows it. An incomplete
    certificate raises. ``told`` is called after each answer.
    """
    for _, _, kind in query_points:
        if kind not in QUERY_KINDS or kind == "pairs" and pairs is None or kind == "cut" and cut_rows is None:
            raise ValueError(f"a query of kind {kind} is unknown or lacks its rows")
    sketch: GraphSketch | None = None
    done = -1
    cache = ForestCache(vertices)
    at_cached = -1
    peeled: tuple[int, DataFrame] | None = None
    out = []

    def between(after: int, upto: int) -> DataFrame:
        return updates.where((F.col("seq") > after) & (F.col("seq") <= upto))

    def at(seq: int) -> Callable[[], GraphSketch]:
        def build() -> GraphSketch:
            nonlocal sketch, done
            if sketch is None:
                sketch = GraphSketch.build(between(done, seq), params, policy, epoch=seq)
            elif seq > done:
                sketch = sketch.advance(between(done, seq), seq, policy)
            done = max(done, seq)
            return sketch

        return build

    def certified(seq: int) -> tuple[str, DataFrame]:
        nonlocal peeled
        state = "exact"
        if peeled is None or not cached or not between(peeled[0], seq).isEmpty():
            state = "cold"
            made, complete = certificate.peel(at(seq)(), params.copies, vertices)
            if not complete:
                raise RuntimeError(f"the certificate at {seq} is incomplete")
            peeled = seq, materialize(made, "certificate")
        return state, peeled[1]

    for query_id, seq, kind in sorted(query_points, key=lambda q: (q[1], q[0])):
        if not cached:
            cache = ForestCache(vertices)
            at_cached = -1
        if kind in ("kconn", "cut"):
            state, result = certified(seq)
            if kind == "cut":
                result = cuts.cut_values(result, cut_rows, params.copies)
        elif kind == "pairs":
            held = cache.at_seq
            result = cache.reachable(pairs, between(at_cached, seq), at(seq), seq)
            at_cached = seq if cache.at_seq != held else at_cached
            state = cache.last_state
        else:
            result = cache.query(at(seq), between(at_cached, seq), seq)
            at_cached, state = seq, cache.last_state
        out.append((query_id, state, result))
        if told is not None:
            told(query_id, result)
    return out


def live_counts(stream: DataFrame, every: str = "30 days", late: str = "1 hour") -> DataFrame:
    """Inserts and deletes in tumbling windows of event time, with a watermark."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", every).alias("w")).agg(F.count(F.when(F.col("delta") > 0, 1)).alias("inserts"), F.count(F.when(F.col("delta") < 0, 1)).alias("deletes"))


def batch_equals_stream(updates: DataFrame, upto: int | None = None) -> DataFrame:
    """What a stream's sketch must answer: the live edges of the prefix."""
    return live_edges(updates, upto)
