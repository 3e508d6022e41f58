"""Accuracy measures: sampler failure and uniformity, and answers against exact ones."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.functions.sampler import EDGE, SamplerKernel, SketchParams
from edgesketch.operators.forest import ForestResult


def sampler_trials(support: int, trials: int, variant: str = "one_level", columns: int = 1, v: int = 4096, seed: int = 1) -> tuple[float, np.ndarray, np.ndarray]:
    """(success share, ids, how often each was sampled) of one sampler over random vectors of a support size."""
    rng = np.random.default_rng(seed)
    pairs = rng.choice(v * (v - 1) // 2, support, replace=False)
    lo = np.floor((2 * v - 1 - np.sqrt((2.0 * v - 1) ** 2 - 8.0 * pairs)) / 2).astype(np.int64)
    hi = pairs - lo * (2 * v - lo - 1) // 2 + lo + 1
    good = (lo >= 0) & (lo < hi) & (hi < v)
    ids = ((lo[good] << 32) | hi[good]).astype(np.uint64)
    hits, count = 0, np.zeros(len(ids), np.int64)
    kernel = SamplerKernel(SketchParams(v, variant, samplers=trials, columns=columns, seed=seed))
    body = kernel.sketch(np.zeros(len(ids), np.int64), ids, 1)
    one = SamplerKernel(SketchParams(v, variant, samplers=1, columns=columns, seed=seed))
    status, got = one.decode(body.reshape(trials, -1))
    hits = int((status == EDGE).sum())
    at = np.searchsorted(np.sort(ids), got[status == EDGE])
    np.add.at(count, at, 1)
    return hits / trials, np.sort(ids), count


def uniformity(count: np.ndarray) -> float:
    """Chi-squared of sampled edges over its degrees of freedom; near 1 if uniform."""
    mean = count.sum() / len(count)
    return float(((count - mean) ** 2 / mean).sum() / max(1, len(count) - 1))


def compare_components(found: DataFrame, exact: DataFrame) -> dict[str, int]:
    """Vertices, and those whose canonical component differs."""
    met = found.toDF("vertex", "a").join(exact.toDF("vertex", "b"), "vertex", "full")
    r = met.agg(F.count(F.lit(1)).alias("n"), F.count(F.when(~F.col("a").eqNullSafe(F.col("b")), 1)).alias("bad")).first()
    return {"vertices": r.n, "different": r.bad}


def check_forest(result: ForestResult, edges: DataFrame) -> dict[str, int | bool]:
    """Forest edges, those that are no edges of the graph, and whether their number is V minus components."""
    forest = result.forest.select("u", "v")
    n, outside = forest.count(), forest.join(edges.select("u", "v"), ["u", "v"], "left_anti").count()
    r = result.labels.agg(F.count(F.lit(1)).alias("v"), F.countDistinct("component").alias("c")).first()
    return {"edges": n, "outside": outside, "spans": n == r.v - r.c, "distinct": forest.distinct().count() == n}
