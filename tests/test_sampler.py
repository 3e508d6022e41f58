"""Hash families and sampler kernels: linearity, emptiness, variants, success rates."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from edgesketch.functions.hashing import mix64, pair31, pair31_factors, pair31_sql, trailing_zeros
from edgesketch.functions.sampler import EDGE, EMPTY, FAILED, SamplerKernel, SketchParams, nested_from_one_level
from edgesketch.plans import accuracy, costs, workloads


def ids(pairs):
    return np.array([(u << 32) | v for u, v in pairs], np.uint64)


def sketch(pairs, **kw):
    p = SketchParams(64, samplers=6, **kw)
    k = SamplerKernel(p)
    return p, k, k.sketch(np.zeros(len(pairs), np.int64), ids(pairs), 1)


edge = st.tuples(st.integers(0, 62), st.integers(1, 63)).filter(lambda e: e[0] < e[1])


@settings(max_examples=40, deadline=None)
@given(st.lists(edge, max_size=30), st.lists(edge, max_size=30))
def test_linear(a, b):
    *_, x = sketch(a)
    *_, y = sketch(b)
    *_, both = sketch(a + b)
    assert (x ^ y == both).all()


@settings(max_examples=30, deadline=None)
@given(st.lists(edge, max_size=30))
def test_delete_restores_and_order_does_not_matter(a):
    *_, twice = sketch(a + a[::-1])
    assert not twice.any()
    *_, x = sketch(a)
    *_, y = sketch(a[::-1])
    assert (x == y).all()


@settings(max_examples=30, deadline=None)
@given(st.lists(edge, max_size=30, unique=True))
def test_nested_is_suffix_xor_and_decode_returns_members(a):
    p, k, one = sketch(a)
    *_, nested = sketch(a, variant="nested")
    assert (nested_from_one_level(one, p) == nested).all()
    for body in (one, nested):
        status, got = k.decode(body.reshape(-1, p.words))
        for s, g in zip(status, got):
            assert s == EMPTY if not a else s in (EDGE, FAILED)
            assert s != EDGE or int(g) in {int(x) for x in ids(a)}


def test_complete_graph_vertex_with_id_xor_zero_is_not_empty():
    pairs = [(0, v) for v in range(1, 100)]
    assert np.bitwise_xor.reduce(ids(pairs)) == 0
    p = SketchParams(100)
    body = SamplerKernel(p).sketch(np.zeros(99, np.int64), ids(pairs), 1).reshape(-1, p.words)
    status, _ = SamplerKernel(p).decode(body)
    assert (status != EMPTY).all()


def test_lone_edge_is_always_found():
    p, k, body = sketch([(3, 9)])
    status, got = k.decode(body.reshape(-1, p.words))
    assert (status == EDGE).all() and (got == ids([(3, 9)])[0]).all()


def test_success_rates_and_uniformity():
    expected = {"one_level": {1: 1.0, 2: 0.671, 3: 0.859, 10: 0.814, 100: 0.81}, "nested": {1: 1.0, 2: 0.671, 3: 0.723, 10: 0.719, 100: 0.717}}
    for variant, by in expected.items():
        for support, share in by.items():
            found, _, count = accuracy.sampler_trials(support, 3000, variant)
            assert abs(found - share) < 4 * (share * (1 - share) / 3000) ** 0.5 + 0.012
            if support == 10:
                assert accuracy.uniformity(count) < 4


def test_trailing_zeros_and_mix():
    h = np.array([0, 1, 2, 12, 1 << 63], np.uint64)
    assert trailing_zeros(h).tolist() == [64, 0, 1, 2, 63]
    assert len(np.unique(mix64(np.arange(10000, dtype=np.uint64), 5))) == 10000


def test_pair31_is_the_same_in_spark(spark):
    from pyspark.sql import functions as F

    lo, hi = np.arange(50), np.arange(50) * 7 + 1
    a, b, c = (F.lit(x).cast("long") for x in pair31_factors(9))
    got = [r[0] for r in spark.range(50).select(pair31_sql(F.col("id"), F.col("id") * 7 + 1, a, b, c)).collect()]
    assert got == pair31(lo, hi, 9).tolist()


def test_params_and_costs():
    with pytest.raises(ValueError):
        SketchParams(10, variant="other")
    p = SketchParams(1 << 18)
    assert p.samplers == 31 and costs.hash_calls(p) == 126
    for share, near in ((1.0, 436_000), (0.5, 988_500)):
        v = costs.crossover(costs.model_bytes, share)
        assert abs(v - near) < 1000
        assert costs.model_bytes(v) < share * v * v / 8 and costs.model_bytes(v - 1) >= share * (v - 1) ** 2 / 8
    assert costs.model_bytes(1 << 17) / 2**30 == pytest.approx(5.45, abs=0.01)
    assert costs.worker_bytes(1 << 30, 1) == 142_680
    assert costs.traffic_bound(2, 0.5, 1) == 4
    assert costs.advise(10**4, 10**9) == "sketch" and costs.advise(10**6, 10**6) == "exact"
    for k in (2, 4, 8):
        assert SketchParams(1000, copies=k).vertex_bytes == k * SketchParams(1000).vertex_bytes


def test_counted_work_matches_the_formulas():
    work = workloads.counted_work(4000)
    one, nested = (SketchParams(4096, v) for v in ("one_level", "nested"))
    assert work["one_level"][0] == costs.buckets_examined(one) and work["nested"][0] == costs.buckets_examined(nested)
    written = costs.bucket_writes(nested) - nested.samplers
    assert work["nested"][1] == pytest.approx(written, rel=0.02)
    assert work["nested"][0] > 10 * work["one_level"][0]
