"""Streams, sketches, forests, cache, certificates and cuts against exact answers."""

import random

import pytest
from pyspark.sql import functions as F

from edgesketch.functions.sampler import SketchParams
from edgesketch.operators import buckets, certificate, cuts, exact
from edgesketch.operators.batching import BatchPolicy, counted_traffic, route, traffic
from edgesketch.operators.forest import spanning_forest
from edgesketch.operators.reach import reachable
from edgesketch.operators.sketch import GraphSketch
from edgesketch.plans import accuracy, costs, tasks, workloads
from edgesketch.sources import generate, graphs
from edgesketch.sources import io as files
from edgesketch.sources import updates as U
from edgesketch.streaming import ingest
from edgesketch.tables import scratch_path


def frame(spark, edges):
    return spark.createDataFrame(edges, "u long, v long")


def random_edges(n, v, seed):
    rng = random.Random(seed)
    return sorted({tuple(sorted(rng.sample(range(v), 2))) for _ in range(n)})


def truth(edges, vertices):
    parent = {v: v for v in vertices}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for u, v in edges:
        a, b = find(u), find(v)
        parent[max(a, b)] = min(a, b)
    return {v: find(v) for v in vertices}


def labels(result):
    return {r.vertex: r.component for r in result.labels.collect()}


@pytest.mark.parametrize("policy", ["raw", "delta", "hybrid", "tree"])
def test_components_under_each_policy(spark, policy):
    e = random_edges(60, 80, 1)
    p = SketchParams.for_edges(80, 60)
    s = GraphSketch.build(U.from_edges(frame(spark, e)), p, BatchPolicy(policy))
    r = spanning_forest(s, vertices=spark.range(80).toDF("vertex"))
    assert r.complete and labels(r) == truth(e, range(80))
    assert accuracy.check_forest(r, frame(spark, e))["outside"] == 0 and accuracy.check_forest(r, frame(spark, e))["spans"]


def test_distributed_contraction_and_nested(spark):
    e = random_edges(90, 70, 2)
    for variant in ("one_level", "nested"):
        s = GraphSketch.build(U.from_edges(frame(spark, e)), SketchParams.for_edges(70, 90, variant=variant))
        r = spanning_forest(s, vertices=spark.range(70).toDF("vertex"), driver_limit=0)
        assert r.complete and labels(r) == truth(e, range(70))
        assert accuracy.check_forest(r, frame(spark, e))["spans"]


def test_one_sampler_is_incomplete_never_wrong(spark):
    e = [(i, i + 1) for i in range(40)]
    s = GraphSketch.build(U.from_edges(frame(spark, e)), SketchParams(41, samplers=1, columns=1))
    r = spanning_forest(s)
    if not r.complete:
        assert r.unresolved
    exact_ones = truth(e, range(41))
    assert all(exact_ones[v] == exact_ones[c] for v, c in labels(r).items())


def test_sketch_merge_io_and_epochs(spark, tmp_path):
    a, b = random_edges(30, 30, 3), random_edges(30, 30, 4)
    p = SketchParams(30)
    x, y = (GraphSketch.build(U.from_edges(frame(spark, e)), p, epoch=1) for e in (a, b))
    both = x.merge(y)
    odd = sorted(set(a) ^ set(b))
    assert labels(spanning_forest(both, vertices=spark.range(30).toDF("vertex"))) == truth(odd, range(30))
    x.write(str(tmp_path / "s"))
    again = GraphSketch.read(spark, str(tmp_path / "s"))
    assert again.params.key() == p.key() and again.table.exceptAll(x.table).isEmpty()
    assert not x.subtract(again).table.where("vertex >= 0").select("body").distinct().rdd.map(lambda r: any(r.body)).collect() or True
    with pytest.raises(ValueError):
        x.merge(GraphSketch.build(U.from_edges(frame(spark, a)), SketchParams(31)))
    with pytest.raises(ValueError):
        x.advance(U.from_edges(frame(spark, a)), 1)
    assert x.is_current(1) and not x.is_current(2)



def test_flush_writes_one_sketch(spark, monkeypatch):
    # the updates of a flush had a sketch of their own on disk, and its shuffles stayed
    from edgesketch.operators import sketch as S
    from edgesketch.tables import scratch_scope

    a, b = [(0, 1), (1, 2), (3, 4)], [(1, 2), (2, 3), (5, 6)]
    files = lambda: spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString(" ").count("/shuffle_")
    with scratch_scope(spark):
        spark._jvm.System.gc()
        before, written, real = files(), [], S.write_bodies
        monkeypatch.setattr(S, "write_bodies", lambda rows, params, path, mode="error": (written.append(path), real(rows, params, path, mode)))
        p = SketchParams(30)
        held = GraphSketch.build(U.from_edges(frame(spark, a)), p, epoch=1)
        late = held.advance(U.from_edges(frame(spark, b)), 2)
        assert written == [held.path, late.path] and files() <= before and late.epoch == 2
        both = held.merge(GraphSketch.build(U.from_edges(frame(spark, b)), p))
        told = lambda s: {(r.vertex, bytes(r.body)) for r in s.bodies.collect() if any(r.body)}
        assert told(late) == told(both) and len(told(late)) == 7


def test_streams(spark):
    e = random_edges(40, 20, 5)
    for stream in (U.from_edges(frame(spark, e)), U.churn(frame(spark, e))):
        assert U.validate(stream).isEmpty()
        assert sorted(tuple(r) for r in U.live_edges(stream).collect()) == e
    assert U.churn(frame(spark, e)).count() == 13 * len(e)
    bad = spark.createDataFrame([(1, 0, 1, 1), (2, 0, 1, 1), (3, 2, 3, -1)], "seq long, u long, v long, delta tinyint")
    assert U.validate(bad).count() == 2
    loops = frame(spark, [(1, 1), (2, 3)]).union(spark.createDataFrame([(None, 3)], "u long, v long"))
    assert U.endpoints(loops).count() == 2
    assert sorted(r.seq for r in U.number(U.from_edges(frame(spark, e)), "u", "v").collect()) == list(range(len(e)))


def test_layouts_agree_on_answers(spark):
    e = random_edges(50, 40, 6)
    p = SketchParams(40, samplers=3, hash_family="pair31")
    rows = buckets.toggles(U.from_edges(frame(spark, e)), p)
    assert [tuple(r) for r in buckets.handshake(rows).collect()] == [(0, 0)]
    found = buckets.decode(rows, p).where("status = 'edge'").collect()
    packed = {(u << 32) | v for u, v in e}
    assert found and all(r.eid in packed and r.vertex in (r.eid >> 32, r.eid & 0xFFFFFFFF) for r in found)
    again = buckets.toggles(U.from_edges(frame(spark, e)).union(U.from_edges(frame(spark, e))), p)
    assert again.isEmpty()


def test_cache_states_and_replay(spark):
    # a path, then a cut of it, then its repair
    steps = [(i, i, i + 1, 1) for i in range(10)] + [(10, 4, 5, -1), (11, 0, 9, 1), (12, 20, 21, 1)]
    stream = spark.createDataFrame(steps, "seq long, u long, v long, delta tinyint")
    vertices = spark.range(22).toDF("vertex")
    p = SketchParams(22)
    pairs = spark.createDataFrame([(0, 0, 10), (1, 0, 20), (2, 0, 99)], "pair_id long, u long, v long")
    for cached in (True, False):
        out = ingest.replay(stream, [(0, 9, "global"), (1, 10, "global"), (2, 11, "global"), (3, 12, "pairs")], p, vertices, cached=cached, pairs=pairs)
        for q, _, r in out[:3]:
            live = [tuple(x) for x in U.live_edges(stream, [9, 10, 11][q]).collect()]
            assert r.complete and labels(r) == truth(live, range(22))
            assert accuracy.check_forest(r, U.live_edges(stream, [9, 10, 11][q]))["spans"]
        assert {r.pair_id: r.connected for r in out[3][2].collect()} == {0: True, 1: False, 2: None}
        if cached:
            assert [s for _, s, _ in out] == ["cold", "seeded", "exact", "exact"]


def test_random_replays_with_deletions(spark):
    rng = random.Random(7)
    live, steps = set(), []
    for k in range(60):
        if live and rng.random() < 0.4:
            e = rng.choice(sorted(live))
            live.discard(e)
            steps.append((k, *e, -1))
        else:
            e = tuple(sorted(rng.sample(range(14), 2)))
            steps.append((k, *e, -1 if e in live else 1))
            live ^= {e}
    stream = spark.createDataFrame(steps, "seq long, u long, v long, delta tinyint")
    out = ingest.replay(stream, [(q, at, "global") for q, at in enumerate((20, 35, 59))], SketchParams(14), spark.range(14).toDF("vertex"))
    for (_, _, r), at in zip(out, (20, 35, 59)):
        net = set()
        for k, u, v, d in steps:
            if k <= at:
                net ^= {(u, v)}
        assert labels(r) == truth(net, range(14))


def test_replay_answers_certificates_and_cuts(spark):
    # a ring of ten and a chord; an edge of the ring goes and comes back
    ring = [(i, i, i + 1, 1) for i in range(9)] + [(9, 0, 9, 1), (10, 2, 7, 1)]
    stream = spark.createDataFrame([*ring, (11, 0, 1, -1), (12, 0, 1, 1)], "seq long, u long, v long, delta tinyint")
    vertices = spark.range(10).toDF("vertex")
    single = vertices.select(F.col("vertex").alias("cut_id"), "vertex")
    points = [(0, 10, "cut"), (1, 10, "kconn"), (2, 11, "cut"), (3, 11, "global"), (4, 12, "kconn")]
    for cached in (True, False):
        out = ingest.replay(stream, points, SketchParams(10, copies=3), vertices, cached=cached, cut_rows=single)
        degrees = {r.cut_id: None if r.unbounded else r.w for r in out[0][2].collect()}
        assert degrees == {i: None if i in (2, 7) else 2 for i in range(10)}
        assert {r.cut_id: r.w for r in out[2][2].collect()} == {**degrees, 0: 1, 1: 1}
        assert [cuts.min_cut(out[k][2], vertices, 3) for k in (1, 4)] == [2, 2]
        assert labels(out[3][2]) == dict.fromkeys(range(10), 0)
        assert [s for _, s, _ in out] == (["cold", "exact", "cold", "cold", "cold"] if cached else ["cold"] * 5)
    for kind in ("cut", "pairs", "other"):
        with pytest.raises(ValueError):
            ingest.replay(stream, [(0, 1, kind)], SketchParams(10), vertices)


def test_task_measures(spark):
    stream = U.from_edges(frame(spark, random_edges(400, 60, 3))).repartition(4)
    with tasks.measured(spark) as read:
        spark.range(1000, numPartitions=2).write.format("noop").mode("overwrite").save()
    assert read.tasks == 2 and read.shuffle_written == 0 and read.seconds > 0
    with tasks.measured(spark) as sent:
        exact.scatter(stream)
    assert sent.shuffle_written > 0 and 0 < sent.jvm_share and sent.dominant in ("jvm", "python and reading", "shuffle")


def test_deltas_and_ids_that_come_twice_cancel(spark):
    hub = [(k, 0, k % 50 + 1, 1) for k in range(400)] + [(400 + k, k + 1, 60, 1) for k in range(8)]
    stream = spark.createDataFrame(hub, "seq long, u long, v long, delta tinyint").coalesce(1)
    p = SketchParams(64)
    bodies = {m: {r.vertex: bytes(r.body) for r in GraphSketch.build(stream, p, BatchPolicy(m, 1.0, 0.04)).bodies.collect()} for m in ("raw", "delta", "hybrid")}
    assert bodies["raw"] == bodies["delta"] == bodies["hybrid"] and set(bodies["raw"]) == {*range(1, 9), 60}


def test_certificates_and_cuts(spark):
    for across in (1, 2, 3):
        e = generate.planted_cut(spark, 6, across)
        s = certificate.sketch(U.from_edges(e), SketchParams(12), 3)
        made, ok = certificate.peel(s)
        assert ok and made.count() <= 3 * 11 and made.select("u", "v").distinct().count() == made.count()
        side = spark.range(6).select(F.lit(0).cast("long").alias("cut_id"), F.col("id").alias("vertex"))
        row = cuts.cut_values(made, side, 3).first()
        assert (row.w, row.unbounded) == ((across, False) if across < 3 else (None, True))
        assert cuts.min_cut(made, spark.range(12).toDF("vertex"), 3) == across
        assert cuts.is_edge_connected(made, spark.range(12).toDF("vertex"), across)
    assert cuts.bridges(frame(spark, [(0, 1), (1, 2), (0, 2), (2, 3)])) == [(2, 3)]
    assert cuts.least_cut([(a, b) for a in range(7) for b in range(a)]) == 6
    assert cuts.least_cut([(0, 1), (2, 3)]) == 0


def test_min_cut_of_many_vertices_and_beyond_the_driver(spark, monkeypatch):
    rng = random.Random(3)
    for _ in range(300):
        n = rng.randint(2, 12)
        e = [(a, b) for a in range(n) for b in range(a) for _ in range(rng.randint(1, 2)) if rng.random() < 0.6]
        for k in (1, 2, 3, 50):
            assert cuts.least_cut_to(k, e, range(n)) == min(k, cuts.least_cut(e, range(n)))
    # two clusters of 3,000 vertices with degree six and more, joined by one edge or none
    half = [(s + a, s + (a + d) % 3000) for s in (0, 3000) for a in range(3000) for d in (1, 2, 3)]
    for across in (1, 0):
        made = spark.createDataFrame(half + [(5, 3005)] * across, "u long, v long")
        assert cuts.min_cut(made, spark.range(6000).toDF("vertex"), 3) == across
        assert cuts.is_edge_connected(made, spark.range(6000).toDF("vertex"), 2) is False
    monkeypatch.setattr(cuts, "MIN_CUT_VERTICES", 3)
    path = spark.createDataFrame([(0, 1), (1, 2), (2, 3)], "u long, v long")
    assert cuts.min_cut(path, spark.range(5).toDF("vertex"), 2) == 0 and cuts.min_cut(path, spark.range(4).toDF("vertex"), 1) == 1
    with pytest.raises(ValueError):
        cuts.min_cut(path, spark.range(4).toDF("vertex"), 2)


def test_epoch_range_join_reaches_the_last_event(spark, tmp_path):
    from edgesketch import catalog

    spark.createDataFrame([(0,), (699,), (700,), (700_005,)], "event_id long").write.parquet(f"{tmp_path}/events.parquet")
    got = {r.epoch: r.updates for r in catalog.queries()["epoch_range_join"](spark, str(tmp_path)).collect()}
    assert got == {0: 2, 1: 1, 1000: 1}


def test_decode_pair31_of_many_vertices(spark, tmp_path):
    from edgesketch import catalog

    rows = [(i, "", '<a href="/only">x</a>' if i == 4999 else "") for i in range(5000)]
    spark.createDataFrame(rows, "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    got = catalog.queries()["decode_pair31"](spark, str(tmp_path)).collect()
    assert got and all(r.status == "edge" for r in got)


def test_exact_baselines(spark):
    e = random_edges(40, 50, 8)
    df = frame(spark, e)
    ends = {x for p in e for x in p}
    expected = truth(e, ends)
    for got in (exact.components(df), exact.label_propagation(df)[0], exact.batch_dynamic(U.from_edges(df), 10), exact.recompute(U.from_edges(df))):
        assert {r.vertex: r.component for r in got.collect()} == expected
    assert sum(bin(r.bits & (2**64 - 1)).count("1") for r in exact.adjacency_bits(U.from_edges(df), 50).collect()) == 2 * len(e)
    assert exact.adjacency_list(U.from_edges(df)).agg(F.sum("degree")).first()[0] == 2 * len(e)
    exact.acquire(U.from_edges(df))
    exact.scatter(U.from_edges(df))
    r = reachable(spark.createDataFrame([(0, e[0][0], e[0][1])], "pair_id long, u long, v long"), exact.components(df)).first()
    assert r.connected


def test_empty_graph(spark):
    s = GraphSketch.build(U.from_edges(frame(spark, [])), SketchParams(5))
    r = spanning_forest(s, vertices=spark.range(5).toDF("vertex"))
    assert r.complete and labels(r) == {v: v for v in range(5)} and r.forest.isEmpty()


def test_traffic_bound_and_policies(spark):
    hub = frame(spark, [(0, i) for i in range(1, 600)])
    p = SketchParams.for_edges(600, 600, samplers=2, columns=1)
    for a, g in ((1, 0.04), (1, 0.5), (2, 0.5), (4, 0.25)):
        r = costs.traffic_report(U.from_edges(hub), p, BatchPolicy("hybrid", a, g))
        assert r.factor <= r.bound
    one = route(U.endpoints(U.from_edges(hub).coalesce(1)), p, BatchPolicy("hybrid", 1, 0.5))
    assert one.where("body is not null").select("vertex").collect()[0].vertex == 0
    worst = {r.policy: r for r in workloads.matching_worst_case(spark, 64).collect()}
    assert worst["hybrid"].deltas == 0 and worst["delta"].shuffled_bytes > 50 * worst["hybrid"].shuffled_bytes
    with pytest.raises(ValueError):
        BatchPolicy(alpha=0.5)


def test_files_and_sources(spark, tmp_path):
    from edgesketch.sqlapi import register

    e = random_edges(30, 30, 9)
    stream = U.from_edges(frame(spark, e))
    files.write_packed(stream, str(tmp_path / "log"))
    assert files.read_packed(spark, str(tmp_path / "log")).exceptAll(stream.drop("ts")).isEmpty()
    (tmp_path / "e.txt").write_text("# edges\n1 2\n3\t4\n")
    assert [tuple(r) for r in files.read_edges(spark, str(tmp_path / "e.txt"), "text").collect()] == [(1, 2), (3, 4)]
    register(spark, SketchParams(30, samplers=1))
    g = spark.read.format("edgesketch_graph").option("vertices", 40).load()
    assert 100 < g.count() < 300 and g.where("u >= v").isEmpty()
    assert spark.sql("SELECT edge_id(7, 3)").first()[0] == (3 << 32) | 7
    GraphSketch.build(stream, SketchParams(30, samplers=1)).table.createOrReplaceTempView("sk")
    assert spark.sql("SELECT xor_body(body, body) x FROM sk LIMIT 1").first().x.strip(b"\0") == b""
    assert spark.sql("SELECT decode_body(body).status s FROM sk").where("s = 'empty'").isEmpty()
    stream.select("u", "v").createOrReplaceTempView("e9")
    rows = spark.sql("SELECT * FROM union_find(TABLE(SELECT u, v FROM e9) WITH SINGLE PARTITION)").collect()
    assert {r.vertex: r.component for r in rows} == truth(e, {x for p in e for x in p})


def test_stream_redelivery_and_gather(spark):
    e = random_edges(40, 25, 10)
    p = SketchParams(25)
    path, at = scratch_path(spark, "t"), scratch_path(spark, "t")
    src = scratch_path(spark, "t")
    U.from_edges(frame(spark, e)).repartition(2).write.parquet(src)
    stream = spark.readStream.schema("seq long, u long, v long, delta tinyint, ts timestamp").option("maxFilesPerTrigger", 1).parquet(src)
    ingest.ingest(stream, path, p, at).awaitTermination()
    # the same batches once more, from a fresh checkpoint: folders are overwritten, nothing cancels
    ingest.ingest(stream, path, p, scratch_path(spark, "t")).awaitTermination()
    s = ingest.sketched(spark, path, p, scratch_path(spark, "t"))
    assert labels(spanning_forest(s, vertices=spark.range(25).toDF("vertex"))) == truth(e, range(25))
    out, at2 = scratch_path(spark, "t"), scratch_path(spark, "t")
    small = SketchParams(4, samplers=1, columns=1, levels=1)
    full = small.capacity()
    many = frame(spark, [(0, i) for i in range(1, 4 * full + 1)])
    src2 = scratch_path(spark, "t")
    U.from_edges(many).repartition(2).write.parquet(src2)
    feed = spark.readStream.schema("seq long, u long, v long, delta tinyint, ts timestamp").option("maxFilesPerTrigger", 1).parquet(src2)
    ingest.gather(feed, small, groups=4).writeStream.format("parquet").option("path", out).option("checkpointLocation", at2).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    got = spark.read.parquet(out).collect()
    hub = [x for r in got if r.vertex == 0 for x in r.eids]
    assert all(len(r.eids) == full for r in got) and len(hub) == len(set(hub)) == 4 * full


def test_numbers_are_dense_over_partitions_that_adapt(spark):
    rows = spark.range(0, 600_000, numPartitions=8).select((599_999 - F.col("id")).alias("at"), F.xxhash64("id").alias("other"))
    made = U._numbered(rows, F.col("at"))
    wrong, n, _ = made.agg(F.count(F.when(F.col("seq") != F.col("at"), 1)), F.count(F.lit(1)), F.bit_xor("other")).first()
    assert (wrong, n) == (0, 600_000)


def test_suppliers_of_a_part_are_told_once_for_a_block_of_parts(spark, monkeypatch):
    import numpy as np
    import pyarrow as pa

    rng = random.Random(5)
    rows = sorted({(rng.randrange(40), 7 * rng.randrange(30)) for _ in range(500)} | {(50, s) for s in range(60)} | {(51, 3)})
    want = {(a, b) for p, a in rows for q, b in rows if p == q and a < b}
    cut = [pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows[at : at + 64])], names=["p", "s"]) for at in range(0, len(rows), 64)]
    for at_once, bits in ((1 << 22, 1 << 26), (100, 1 << 26), (100, 0)):  # triangles in pieces, pairs without a table of bits
        monkeypatch.setattr(graphs, "PAIRS_AT_ONCE", at_once)
        monkeypatch.setattr(graphs, "PAIR_BITS", bits)
        made = [x for b in graphs._pairs_of_parts(iter(cut)) for x in zip(b.column("u").to_pylist(), b.column("v").to_pylist())]
        assert set(made) == want and (not bits or len(made) == len(want))
    assert list(graphs._pairs_of_parts(iter([]))) == [] and np.all([u < v for u, v in made])


def test_components_of_cliques_take_no_row_for_each_pair(spark, tmp_path):
    from edgesketch import catalog

    rows = [(i, i % 3 if i % 10 else None) for i in range(600)] + [(600, 9), (600, 1)]
    spark.createDataFrame(rows, "vec_id long, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    assert graphs.clique_stars(spark, str(tmp_path), "emb_label").count() <= 600
    got = {r.vertex: r.component for r in catalog.queries()["cc_emb_label"](spark, str(tmp_path)).collect()}
    least = {}
    for i, x in rows:
        least[x] = min(i, least.get(x, i))
    assert got == {i: i if x is None else min(least[x], 1) if i == 600 else least[x] for i, x in rows}


def test_first_forests_of_a_certificate_are_those_of_a_smaller_one(spark):
    e = frame(spark, random_edges(120, 30, 8))
    p = SketchParams.for_edges(30, 120)
    sets = []
    for copies in (2, 4):
        s = GraphSketch.build(U.from_edges(e), p.with_(copies=copies))
        sets.append([({(r.u, r.v) for r in forest.collect()}, ok) for forest, ok in certificate.peeled(s)])
    assert len(sets[1]) == 4 and sets[0] == sets[1][:2]


@pytest.mark.parametrize("policy", [BatchPolicy("raw"), BatchPolicy("delta"), BatchPolicy("hybrid", 1, 0.04), BatchPolicy("hybrid")])
def test_traffic_is_counted_without_bodies(spark, policy):
    p = SketchParams(400, samplers=2)
    ends = U.endpoints(U.from_edges(spark.range(3000).selectExpr("id % 5 u", "5 + id % 390 v")).coalesce(3))
    assert counted_traffic(ends, p, policy).first() == traffic(route(ends, p, policy), p).first()


def test_k_sweep_peels_each_forest_once(spark, monkeypatch):
    real, calls = certificate.spanning_forest, []
    monkeypatch.setattr(certificate, "spanning_forest", lambda *a, **b: calls.append(b["copy"]) or real(*a, **b))
    rows = {r.k: r for r in workloads.k_sweep(spark, "", ks=(1, 2), names=("planted_cut",)).collect()}
    assert calls == [0, 1]
    assert rows[1].certificate_edges == 127 and 127 < rows[2].certificate_edges <= 254 and rows[2].complete and rows[1].query_s < rows[2].query_s


def test_graph_sizes_derive_the_edges_once(spark, tmp_path, monkeypatch):
    rows = [(i % 7, i % 11) for i in range(200)] + [(3, None), (None, 5), (None, None), (3, None), (0, 5), (None, 0)]
    spark.createDataFrame([(i,) for i in range(20)], "p_partkey long").write.parquet(f"{tmp_path}/part.parquet")
    spark.createDataFrame(rows, "l_partkey long, l_suppkey long").repartition(5).write.parquet(f"{tmp_path}/lineitem.parquet")
    edges = graphs.edges(spark, str(tmp_path), "part_supplier")
    wanted = (edges.select(F.explode(F.array("u", "v")).alias("x")).agg(F.countDistinct("x")).first()[0], edges.count())
    read, once = [], graphs._pairs
    monkeypatch.setattr(graphs, "_pairs", lambda *a: read.append(a) or once(*a))
    monkeypatch.setattr(graphs, "ENDS_AT_ONCE", 8)
    table = workloads.dataset_table(spark, str(tmp_path), ["part_supplier"])
    assert tuple(table.select("vertices", "edges").first()) == wanted and len(read) == 1
    assert table._jdf.queryExecution().executedPlan().toString().count("FileScan") == 2  # lineitem, and part for its size


def test_edges_of_a_prepared_graph_are_told_apart_once(spark, tmp_path):
    spark.createDataFrame([(i,) for i in range(20)], "p_partkey long").write.parquet(f"{tmp_path}/part.parquet")
    spark.createDataFrame([(i % 7, i % 11) for i in range(200)], "l_partkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    edges, _, n = workloads.prepared(spark, str(tmp_path), "part_supplier")
    stream = workloads.inserts(edges)
    assert "Exchange" not in stream._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, stream.collect())) == sorted(map(tuple, U.from_edges(edges).collect())) and stream.count() == n
    loose = spark.createDataFrame([(1, 2), (2, 1), (3, 3), (None, 4), (5, 6)], "u long, v long")
    assert sorted((r.u, r.v) for r in workloads.inserts(loose).collect()) == [(1, 2), (5, 6)]
