"""Cost measures: bytes, traffic and its bound, hash calls, bucket writes, models and advice."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.functions.sampler import UPDATE_BYTES, SketchParams
from edgesketch.operators.batching import BatchPolicy, counted_traffic
from edgesketch.sources.updates import endpoints

#: Fixed values of the published space model: bytes for each vertex and for each earlier sampler, and their ratio.
MODEL_BYTES, EARLIER_SAMPLER_BYTES, SPACE_RATIO = 164, 56, 2 / 7


def model_bytes(v: int, k: int = 1) -> float:
    """Sketch and buffers on the main node."""
    lg = math.log2(v)
    return MODEL_BYTES * v * (lg * lg - lg) * k


def worker_bytes(v: int, threads: int, k: int = 1) -> float:
    """One sketch and one batch for each thread."""
    lg = math.log2(v)
    return threads * MODEL_BYTES * (lg * lg - lg) * k


def sampler_bytes(variant: str, n: float, delta: float) -> float:
    """M6: bytes of one sampler that fails with at most delta on a vector of length n."""
    earlier = EARLIER_SAMPLER_BYTES * math.log2(1 / delta) * math.log2(n)
    return earlier if variant == "nested" else earlier * SPACE_RATIO


def crossover(bytes_of, bits: float = 1.0, top: int = 1 << 40) -> int:
    """C14: the least V at which ``bytes_of(V)`` is below a bit matrix of ``bits`` V*V bits."""
    lo, hi = 2, top
    while lo < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if bytes_of(mid) < bits * mid * mid / 8 else (mid + 1, hi)
    return lo


def traffic_bound(alpha: float, gamma: float, n: int) -> float:
    """Bytes of receiving, batches and deltas, as a multiple of n updates."""
    return (3 + 1 / (gamma * alpha)) * n


def hash_calls(params: SketchParams) -> int:
    """Hashes for each update, both ends: one level hash a column and sampler, one checksum."""
    return 2 * params.copies * (params.samplers * params.columns) + 2


def bucket_writes(params: SketchParams) -> float:
    """Expected buckets written for each end of an update: 1 a column, or 2 up to a nested level."""
    each = 1.0 if params.variant == "one_level" else 2.0 - 2.0 ** (1 - params.levels)
    return params.copies * params.samplers * (params.columns * each + 1)


def buckets_examined(params: SketchParams) -> int:
    """Levels looked at for each end: 1 a column, or all of them in the nested sampler."""
    each = 1 if params.variant == "one_level" else params.levels
    return params.copies * params.samplers * params.columns * each


def sketch_bytes(params: SketchParams, vertices: int) -> int:
    return vertices * params.vertex_bytes


@dataclass
class Report:
    """C2 in the published accounting (received, batches, deltas) and in what our one shuffle carries."""

    updates: int
    raw_ids: int
    deltas: int
    shuffled_bytes: int
    published_bytes: int
    factor: float
    bound: float


def traffic_report(updates: DataFrame, params: SketchParams, policy: BatchPolicy) -> Report:
    n = updates.count()
    t = counted_traffic(endpoints(updates), params, policy).first()
    shuffled = t.raw_bytes + t.delta_bytes
    # a batch that becomes a delta went out as ids and came back as a body; raw ones are local
    published = n * UPDATE_BYTES + t.updates_in_deltas * UPDATE_BYTES + t.delta_bytes
    return Report(n, t.raw_ids, t.deltas, shuffled, published, published / max(1, n * UPDATE_BYTES), traffic_bound(policy.alpha, policy.gamma, 1))


def leaf_fullness(updates: DataFrame, params: SketchParams, alpha: float = 1.0, bins: int = 10) -> DataFrame:
    """C17: how full the vertex batches of each map partition are at a flush: (tenth, leaves, updates)."""
    full = params.capacity(alpha)
    leaves = endpoints(updates).groupBy(F.spark_partition_id().alias("p"), "vertex").agg(F.count(F.lit(1)).alias("n"))
    tenth = F.least(F.floor(F.col("n") * bins / full), F.lit(bins)).cast("int")
    return leaves.groupBy(tenth.alias("tenth")).agg(F.count(F.lit(1)).alias("leaves"), F.sum("n").alias("updates"))


def moves_per_update(updates: DataFrame, params: SketchParams, policy: BatchPolicy) -> int:
    """How often an update crosses the network until it is in the sketch: the shuffles of the plan."""
    from edgesketch.operators.batching import sketched_rows

    plan = sketched_rows(endpoints(updates), params, policy)._jdf.queryExecution().executedPlan().toString()
    return plan.count("Exchange hashpartitioning") + plan.count("Exchange rangepartitioning")


def main_node(params: SketchParams, vertices: int) -> dict[str, int]:
    """C11: bytes that the driver holds for a contraction (vertex, root and flag of each), and rounds at most."""
    return {"driver_bytes": 17 * vertices, "rounds": params.samplers, "sketch_bytes": sketch_bytes(params, vertices)}


def timed(action) -> tuple[float, object]:
    at = time.perf_counter()
    out = action()
    return time.perf_counter() - at, out


def ingest_rate(updates: DataFrame, build) -> float:
    """Updates a second until all are in the sketch."""
    n = updates.count()
    seconds, _ = timed(build)
    return n / seconds


def bandwidth_ratio(acquire_s: float, scatter_s: float, ingest_s: float) -> dict[str, float]:
    """Slowdown against reading alone, and gain over scattering."""
    return {"against_sequential": ingest_s / acquire_s, "over_random": scatter_s / ingest_s}


def advise(v: int, n: int, params: SketchParams | None = None) -> str:
    """Which way pays: a sketch only where a vertex has more updates than its body has words."""
    p = params or SketchParams(v)
    return "sketch" if 2 * n / max(1, v) > p.vertex_bytes / 8 else "exact"


def bottlenecks(v: int, e: int, n: int, approach: str) -> dict[str, float]:
    """C20: bytes held, work and bytes sent for each update of an approach."""
    lg = math.log2(max(2, v))
    table = {
        "adjacency": (v * v / 8, 1.0, UPDATE_BYTES), "lossless distributed": (16.0 * e, lg, 16.0 * lg), "earlier sketch": (model_bytes(v) / SPACE_RATIO, lg * lg, UPDATE_BYTES),
        "one-level sketch": (model_bytes(v), lg, 3 * UPDATE_BYTES),
    }
    space, cpu, network = table[approach]
    return {"space": float(space), "cpu": float(cpu), "network": float(network), "dominant": max((("space", space / (16.0 * e)), ("cpu", cpu / lg), ("network", network / (3 * UPDATE_BYTES))), key=lambda x: x[1])[0]}
