"""The experiment workloads, re-expressed on the given tables. Each returns a DataFrame of its measures.

Wall times depend on the machine; the laws between rows (which variant wins, how a measure moves with
a parameter) are what is compared with the published ones.
"""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgesketch.functions.sampler import SamplerKernel, SketchParams
from edgesketch.operators import certificate, exact
from edgesketch.operators.batching import BatchPolicy
from edgesketch.operators.forest import spanning_forest
from edgesketch.operators.reach import hashed_pairs
from edgesketch.operators.sketch import GraphSketch
from edgesketch.plans import accuracy, costs, tasks
from edgesketch.sources import generate, graphs
from edgesketch.sources import updates as U
from edgesketch.tables import materialize, scratch_scope, table


def prepared(spark: SparkSession, sf_dir: str, name: str, stars: bool = False) -> tuple[DataFrame, int, int]:
    """(edges in the shared folder, V bound, E) of a named graph (or of the stars of its cliques), or of the two cliques of ``planted_cut``."""
    if name == "planted_cut":
        e = generate.planted_cut(spark, 64, 6)
    else:
        e = (graphs.clique_stars if stars else graphs.edges)(spark, sf_dir, name)
    e = materialize(e, "graph")
    r = e.agg(F.max("v").alias("v"), F.count(F.lit(1)).alias("n")).first()
    return e, int(r.v or 0) + 1, int(r.n)


def inserts(edges: DataFrame) -> DataFrame:
    """The insert stream of a prepared graph, whose edges are told apart again only if some have not u < v."""
    return U.from_edges(edges, U.simple(edges))


def ends_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("u", "v")).alias("vertex")).distinct()


def dataset_table(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> DataFrame:
    """Vertices, edges and stream lengths (inserts once, churned seven times) of each graph."""
    made = None
    for name in names or [*graphs.EDGES]:
        one = graphs.sizes(spark, sf_dir, name).select(F.lit(name).alias("graph"), "vertices", "edges", (F.col("edges") * 13).alias("churn_updates"))
        made = one if made is None else made.union(one)
    return made


def months(spark: SparkSession, sf_dir: str) -> list:
    """(month, i, v, e) of each month of orders: its e orders, and its customers rounded up to v = 2^i, 64 at least."""
    o = table(spark, sf_dir, "orders")
    month = (F.year("o_orderdate") * 12 + F.month("o_orderdate")).cast("int").alias("month")
    told = o.groupBy(month).agg(F.greatest(F.countDistinct("o_custkey"), F.lit(64)).alias("n"), F.count(F.lit(1)).alias("e"))
    bits = F.length(F.bin(F.col("n") - 1)).cast("int")
    return told.select("month", bits.alias("i"), F.expr("shiftleft(1L, length(bin(n - 1)))").alias("v"), "e").collect()  # a row for each month


def density_survey(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> DataFrame:
    """Density of each graph and the bytes of its adjacency list."""
    t = dataset_table(spark, sf_dir, names)
    return t.select("graph", (2.0 * F.col("edges") / (F.col("vertices") * (F.col("vertices") - 1))).alias("density"), (F.col("edges") * 16).alias("list_bytes"))


def ablation(spark: SparkSession, sf_dir: str, name: str = "part_supplier") -> DataFrame:
    """Both samplers under each way of batching, on inserts and on the churned stream: time, levels examined, buckets written."""
    e, v, n = prepared(spark, sf_dir, name)
    rows = []
    for kind, made, total in (("inserts", U.from_edges, n), ("churn", U.churn, 13 * n)):
        with scratch_scope(spark):
            stream = materialize(made(e), "stream")
            for variant, mode in ((x, y) for x in ("nested", "one_level") for y in ("raw", "delta", "hybrid")):
                p = SketchParams.for_edges(v, n, variant=variant)
                with scratch_scope(spark):
                    seconds, _ = costs.timed(lambda p=p, mode=mode, stream=stream: GraphSketch.build(stream, p, BatchPolicy(mode)))
                rows.append((kind, variant, mode, total / seconds, float(costs.buckets_examined(p)), float(costs.bucket_writes(p)), costs.hash_calls(p)))
    return spark.createDataFrame(rows, "stream string, variant string, policy string, updates_per_s double, examined double, written double, hashes int")


def scaling(spark: SparkSession, sf_dir: str, ways=(1, 2, 4), name: str = "part_supplier") -> DataFrame:
    """Rate by parallelism, with the reading and scattering floors."""
    e, v, n = prepared(spark, sf_dir, name)
    stream, rows, base = materialize(U.churn(e), "stream"), [], None
    total = 13 * n
    read_s, _ = costs.timed(lambda: exact.acquire(stream))
    scatter_s, _ = costs.timed(lambda: exact.scatter(stream))
    before = spark.conf.get("spark.sql.shuffle.partitions")
    for w in ways:
        part = stream.coalesce(w)
        try:  # as many tasks on either side of the shuffle
            spark.conf.set("spark.sql.shuffle.partitions", str(w))
            with scratch_scope(spark):
                seconds, _ = costs.timed(lambda part=part: GraphSketch.build(part, SketchParams.for_edges(v, n)))
        finally:
            spark.conf.set("spark.sql.shuffle.partitions", before)
        base = base or seconds
        rows.append((w, total / seconds, base / seconds, *costs.bandwidth_ratio(read_s, scatter_s, seconds).values()))
    return spark.createDataFrame(rows, "parallel int, updates_per_s double, speed_up double, against_sequential double, over_random double")


def communication(spark: SparkSession, sf_dir: str, names=("part_supplier", "order_part", "customer_stars", "page_links"), alphas=(1.0, 2.0), gammas=(0.04, 0.25, 0.5)) -> DataFrame:
    """Published accounting of traffic by graph and parameters, with the bound it must keep."""
    rows = []
    for name in names:
        with scratch_scope(spark):
            e, v, n = prepared(spark, sf_dir, name)
            stream = inserts(e)
            for a in alphas:
                for g in gammas:
                    r = costs.traffic_report(stream, SketchParams.for_edges(v, n), BatchPolicy("hybrid", a, g))
                    rows.append((name, a, g, r.updates, r.factor, r.bound, r.factor <= r.bound))
    return spark.createDataFrame(rows, "graph string, alpha double, gamma double, updates long, factor double, bound double, within boolean")


def many_datasets(spark: SparkSession, sf_dir: str, names=None) -> DataFrame:
    """Rate, traffic against its bound, share processed locally, and our body against the list, of every graph."""
    rows = []
    for name in names or [*graphs.EDGES]:
        e, v, n = prepared(spark, sf_dir, name)
        if not n:
            continue
        p, policy, stream = SketchParams.for_edges(v, n), BatchPolicy("hybrid", 1.0, 0.04), inserts(e)
        r = costs.traffic_report(stream, p, policy)
        with scratch_scope(spark):
            seconds, _ = costs.timed(lambda p=p, stream=stream, policy=policy: GraphSketch.build(stream, p, policy))
        rows.append((name, n, n / seconds, r.factor, r.bound, r.raw_ids / (2 * n), costs.sketch_bytes(p, v) / (16 * n), costs.advise(v, n, p)))
    return spark.createDataFrame(rows, "graph string, updates long, updates_per_s double, factor double, bound double, local_share double, bytes_to_list double, advice string")


def traffic_by_queries(spark: SparkSession, sf_dir: str, name: str = "part_supplier", counts=(1, 2, 4)) -> DataFrame:
    """Traffic when Q queries cut a churned stream, each flushing what is pending: it keeps its bound for any Q."""
    e, v, n = prepared(spark, sf_dir, name)
    stream, p, policy = materialize(U.churn(e), "stream"), SketchParams.for_edges(v, n), BatchPolicy("hybrid", 1.0, 0.04)
    top, rows = stream.agg(F.max("seq")).first()[0] + 1, []
    for q in counts:
        published = updates = 0
        for k in range(q):
            r = costs.traffic_report(stream.where((F.col("seq") >= top * k // q) & (F.col("seq") < top * (k + 1) // q)), p, policy)
            published, updates = published + r.published_bytes, updates + r.updates
        rows.append((q, updates, published / (updates * costs.UPDATE_BYTES), costs.traffic_bound(1.0, 0.04, 1)))
    return spark.createDataFrame(rows, "queries int, updates long, factor double, bound double").withColumn("within", F.col("factor") <= F.col("bound"))


def matching_worst_case(spark: SparkSession, v: int = 512, edges: DataFrame | None = None) -> DataFrame:
    """A perfect matching (of ``v`` vertices, or the given one) under each policy: deltas cost a body an end, the hybrid policy stays raw."""
    rows = []
    if edges is None:
        edges = generate.matching(spark, v)
    else:
        v = int(edges.agg(F.max("v")).first()[0] or 0) + 1
    for mode in ("raw", "delta", "hybrid"):
        r = costs.traffic_report(U.from_edges(edges), SketchParams(v), BatchPolicy(mode))
        rows.append((mode, r.updates, r.raw_ids, r.deltas, r.shuffled_bytes))
    return spark.createDataFrame(rows, "policy string, updates long, raw_ids long, deltas long, shuffled_bytes long")


def query_split(spark: SparkSession, sf_dir: str, name: str = "part_supplier") -> DataFrame:
    """Flush (the last tenth of a churned stream into the sketch) and contraction, in seconds."""
    e, v, n = prepared(spark, sf_dir, name)
    with scratch_scope(spark):  # the contraction reads the flushed sketch alone
        stream = materialize(U.churn(e), "stream")
        last = stream.agg(F.max("seq")).first()[0]
        cut = last - last // 10
        held = GraphSketch.build(stream.where(F.col("seq") <= cut), SketchParams.for_edges(v, n), epoch=cut)
        flush, s = costs.timed(lambda: held.advance(stream.where(F.col("seq") > cut), last, outer=1))
    contract, r = costs.timed(lambda: spanning_forest(s))
    return spark.createDataFrame([(name, flush, contract, r.rounds, r.complete)], "graph string, flush_s double, contract_s double, rounds int, complete boolean")


def query_bursts(spark: SparkSession, sf_dir: str, queries: int = 4) -> DataFrame:
    """A burst of queries within 50 updates, with and without the forest cache."""
    from edgesketch.streaming.ingest import replay

    stream, vertices, v, n = user_key_stream(spark, sf_dir)
    last = stream.agg(F.max("seq")).first()[0]
    pairs, rows = materialize(hashed_pairs(spark, 1000, v), "pairs"), []
    for kind in ("global", "pairs"):
        # the first of a burst is cold; the others ask what ``kind`` says
        points = [(k, last - 50 + 50 * k // queries, kind if k else "global") for k in range(queries)]
        for cached in (True, False):
            seconds, at = [], [time.perf_counter()]

            def told(_, result, seconds=seconds, at=at):
                getattr(result, "labels", result).count()
                seconds.append(time.perf_counter() - at[0])
                at[0] = time.perf_counter()

            out = replay(stream, points, SketchParams.for_edges(v, n), vertices, cached=cached, pairs=pairs, told=told)
            rows += [(kind, cached, k + 1, s, out[k][1]) for k, s in enumerate(seconds)]
    return spark.createDataFrame(rows, "kind string, cached boolean, position int, seconds double, last_state string")


def user_key_stream(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, int, int]:
    """(toggle stream of user-key edges with seq = event_id, all vertices, V bound, most edges)."""
    text = f"SELECT event_id AS seq, u, v FROM ({graphs.EDGES['user_key'].format(**graphs.SPARK).replace('SELECT user_id AS u', 'SELECT event_id, user_id AS u')})"
    graphs.views(spark, sf_dir, text)
    rows = spark.sql(text).selectExpr("cast(seq as long) seq", "cast(u as long) u", "cast(v as long) v")
    stream = materialize(U.toggle(rows, "seq"), "stream")
    vertices = materialize(ends_of(stream), "vertices")
    r = stream.agg(F.max("v").alias("v"), F.countDistinct("u", "v").alias("n")).first()
    return stream, vertices, int(r.v) + 1, int(r.n)


def k_sweep(spark: SparkSession, sf_dir: str, ks=(1, 2, 4, 8), names=("part_supplier", "supplier_supplier", "planted_cut")) -> DataFrame:
    """Rate, bytes, query time and traffic by k, side by side.

    A sketch is built for each k. The forests of the largest certificate are those of every smaller one, so they
    are peeled once, and the query of k is timed up to its k-th forest.
    """
    rows = []
    for name in names:
        e, v, n = prepared(spark, sf_dir, name)
        built, told = {}, []
        with scratch_scope(spark):
            for k in sorted(ks):
                p = SketchParams.for_edges(v, n, copies=k)
                if k == max(ks):
                    built[k], s = costs.timed(lambda p=p, e=e: GraphSketch.build(U.from_edges(e), p))
                else:
                    with scratch_scope(spark):
                        built[k], _ = costs.timed(lambda p=p, e=e: GraphSketch.build(U.from_edges(e), p))
            began = time.perf_counter()
            for forest, ok in certificate.peeled(s, max(ks)):
                told.append((time.perf_counter() - began, forest, ok))
            told = [(seconds, forest.count(), ok) for seconds, forest, ok in told]
        for k in ks:
            p, upto = SketchParams.for_edges(v, n, copies=k), told[:k]
            r = costs.traffic_report(U.from_edges(e), p, BatchPolicy())
            rows.append((name, k, n / built[k], p.vertex_bytes, costs.hash_calls(p), upto[-1][0], r.factor, sum(x for _, x, _ in upto), all(ok for *_, ok in upto)))
    return spark.createDataFrame(rows, "graph string, k int, updates_per_s double, vertex_bytes long, hashes int, query_s double, factor double, certificate_edges long, complete boolean")


def certificate_sizes(spark: SparkSession, sf_dir: str, ks=(1, 2, 4), names=("user_key", "page_links", "conversations", "month_part_supplier")) -> DataFrame:
    """What does not depend on time: certificates of further graphs keep their bound and span all at every k."""
    rows = []
    for name in names:
        e, v, n = prepared(spark, sf_dir, name)
        ends = materialize(ends_of(e), "ends")
        held = ends.count()
        with scratch_scope(spark):  # one sketch of the most copies: the first forests of its certificate are those of a smaller k
            s = GraphSketch.build(U.from_edges(e), SketchParams.for_edges(v, n, copies=max(ks)))
            told = [(forest.count(), ok) for forest, ok in certificate.peeled(s, max(ks), ends)]
        rows += [(name, k, told[0][0], sum(x for x, _ in told[:k]) <= k * (held - 1), all(ok for _, ok in told[:k])) for k in ks]
    return spark.createDataFrame(rows, "graph string, k int, first_forest long, bounded boolean, complete boolean")


def update_rate_vs_bits(spark: SparkSession, sf_dir: str, name: str = "part_supplier") -> DataFrame:
    """The sketch, the earlier sketch and the bit matrix over the same stream."""
    e, v, n = prepared(spark, sf_dir, name)
    stream = materialize(U.churn(e), "stream")
    ways = {
        "one_level hybrid": lambda: GraphSketch.build(stream, SketchParams.for_edges(v, n)),
        "nested raw": lambda: GraphSketch.build(stream, SketchParams.for_edges(v, n, variant="nested"), BatchPolicy("raw")),
        "bit matrix": lambda: exact.adjacency_bits(stream, v).write.format("noop").mode("overwrite").save(),
    }
    return spark.createDataFrame([(k, 13 * n / costs.timed(f)[0]) for k, f in ways.items()], "way string, updates_per_s double")


def space_curve(spark: SparkSession, top: int = 22) -> DataFrame:
    """Model, our body and bit matrix by V = 2^i."""
    rows = [(1 << i, costs.model_bytes(1 << i), float((1 << i) * SketchParams(1 << i).vertex_bytes), float(1 << (2 * i)) / 8) for i in range(6, top)]
    return spark.createDataFrame(rows, "v long, model_bytes double, our_bytes double, matrix_bytes double")


def hash_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hashes, levels examined and buckets written for the customers of each month, for both samplers."""
    rows = [(m.month, m.v, variant, costs.hash_calls(p), costs.buckets_examined(p), costs.bucket_writes(p)) for m in months(spark, sf_dir) for variant in ("one_level", "nested") for p in [SketchParams(m.v, variant)]]
    return spark.createDataFrame(rows, "month int, v long, variant string, hashes int, examined int, written double")


def sampler_failure(spark: SparkSession, supports=(1, 2, 3, 10, 100, 1000), trials: int = 2000) -> DataFrame:
    """Success of one column by cut size, and how evenly edges are sampled."""
    rows = []
    for variant in ("one_level", "nested"):
        for s in supports:
            share, _, count = accuracy.sampler_trials(s, trials, variant)
            rows.append((variant, s, share, accuracy.uniformity(count) if s > 1 else 0.0))
    return spark.createDataFrame(rows, "variant string, support int, success double, chi2 double")


def bottleneck_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What dominates each approach on the graph of each month's orders."""
    rows = []
    for m in months(spark, sf_dir):
        for a in ("adjacency", "lossless distributed", "earlier sketch", "one-level sketch"):
            r = costs.bottlenecks(m.v, m.e, 7 * m.e, a)
            rows.append((m.month, a, r["space"], r["cpu"], r["network"], r["dominant"]))
    return spark.createDataFrame(rows, "month int, approach string, space double, cpu double, network double, dominant string")


def measured_bottlenecks(spark: SparkSession, sf_dir: str, name: str = "part_supplier") -> DataFrame:
    """What each approach's tasks did on a churned stream: time, JVM share, bytes shuffled against the stream's, and what dominates."""
    e, v, n = prepared(spark, sf_dir, name)
    stream, total = materialize(U.churn(e), "stream"), 13 * n
    ways = {
        "read": lambda: exact.acquire(stream), "scatter": lambda: exact.scatter(stream),
        "bit matrix": lambda: exact.adjacency_bits(stream, v).write.format("noop").mode("overwrite").save(),
        "adjacency list": lambda: exact.adjacency_list(stream).write.format("noop").mode("overwrite").save(),
        "star components": lambda: exact.components(e).write.format("noop").mode("overwrite").save(),
        "nested raw": lambda: GraphSketch.build(stream, SketchParams.for_edges(v, n, variant="nested"), BatchPolicy("raw")),
        "one-level raw": lambda: GraphSketch.build(stream, SketchParams.for_edges(v, n), BatchPolicy("raw")),
        "one-level hybrid": lambda: GraphSketch.build(stream, SketchParams.for_edges(v, n)),
    }
    rows = []
    for approach, run in ways.items():
        with scratch_scope(spark), tasks.measured(spark) as r:
            run()
        rows.append((approach, r.seconds, r.tasks, r.run_s, r.jvm_share, r.shuffle_written, r.shuffle_written / (total * costs.UPDATE_BYTES), r.spilled, r.dominant))
    return spark.createDataFrame(rows, "approach string, seconds double, tasks int, task_s double, jvm_share double, shuffled_bytes long, shuffled_to_stream double, spilled_bytes long, dominant string")


def counted_work(n: int = 1000, v: int = 4096) -> dict[str, tuple[float, float]]:
    """Levels examined and buckets written for each update by the kernels themselves."""
    import numpy as np

    ids = (np.arange(n, dtype=np.uint64) << np.uint64(32)) | np.uint64(v - 1)
    out = {}
    for variant in ("one_level", "nested"):
        k = SamplerKernel(SketchParams(v, variant))
        k.sketch(np.zeros(n, np.int64), ids, 1)
        out[variant] = k.examined / n, k.written / n
    return out


def provision(v: int) -> int:
    """Samplers for V vertices."""
    return math.ceil(math.log(max(2, v), 1.5))
