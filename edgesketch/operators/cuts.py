"""Bounded cuts from a certificate: w(C) below k, unbounded from k on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.tables import star_components

#: Vertices up to which a global minimum cut is searched on the driver.
MIN_CUT_VERTICES = 200_000
#: Edges of a certificate up to which bridges are searched on the driver.
BRIDGE_EDGES = 2_000_000


def crossing(edges: DataFrame, cuts: DataFrame) -> DataFrame:
    """(cut_id, n): edges with one end in the cut. Each side meets the edges by its own vertices."""
    ends = edges.select("u", "v", F.posexplode(F.array("u", "v")).alias("side", "vertex"))
    met = ends.join(cuts, "vertex").groupBy("cut_id", "u", "v").agg(F.count(F.lit(1)).alias("inside"))
    return met.where("inside = 1").groupBy("cut_id").agg(F.count(F.lit(1)).alias("n"))


def cut_values(certificate: DataFrame, cuts: DataFrame, k: int) -> DataFrame:
    """(cut_id, w, unbounded): w is null from k on."""
    counted = cuts.select("cut_id").distinct().join(crossing(certificate, cuts), "cut_id", "left").select("cut_id", F.coalesce("n", F.lit(0)).alias("n"))
    return counted.select("cut_id", F.when(F.col("n") < k, F.col("n")).cast("long").alias("w"), (F.col("n") >= k).alias("unbounded"))


def _adjacency(edges) -> dict[int, dict[int, int]]:
    near: dict[int, dict[int, int]] = {}
    for u, v in edges:
        near.setdefault(u, {})
        near.setdefault(v, {})
        near[u][v] = near[u].get(v, 0) + 1
        near[v][u] = near[v].get(u, 0) + 1
    return near


def least_cut(edges, vertices=()) -> int:
    """The least cut of a small graph, by repeated maximum-adjacency orders with merging."""
    import heapq

    near = _adjacency(edges)
    for v in vertices:
        near.setdefault(v, {})
    if len(near) < 2:
        return 0
    best = None
    while len(near) > 1:
        start = next(iter(near))
        weight = {v: 0 for v in near}
        heap, seen, order = [(0, start)], set(), []
        while len(order) < len(near):
            v = None
            while heap:
                w, x = heapq.heappop(heap)
                if x not in seen and -w == weight[x]:
                    v = x
                    break
            if v is None:
                return 0  # not connected
            seen.add(v)
            order.append(v)
            for x, w in near[v].items():
                if x not in seen:
                    weight[x] += w
                    heapq.heappush(heap, (-weight[x], x))
        last, before = order[-1], order[-2]
        best = weight[last] if best is None else min(best, weight[last])
        for x, w in near.pop(last).items():
            near[x].pop(last)
            if x != before:
                near[before][x] = near[before].get(x, 0) + w
                near[x][before] = near[x].get(before, 0) + w
    return best or 0


def least_cut_to(k: int, edges, vertices=()) -> int:
    """min(least cut, k): each maximum-adjacency order contracts all edges whose ends no cut below the best one can part.

    When x has gained the weight q by the time an order takes v, v and x are q-connected; the last
    vertex gains its whole degree, so each order contracts something.
    """
    import heapq

    near = _adjacency((u, v) for u, v in edges if u != v)
    for v in vertices:
        near.setdefault(v, {})
    if len(near) < 2:
        return 0
    best = k
    while len(near) > 1:
        best = min(best, min(sum(of.values()) for of in near.values()))
        if best <= 0:
            return 0
        root = {v: v for v in near}

        def find(x, root=root):
            while root[x] != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        weight, seen, heap = dict.fromkeys(near, 0), set(), [(0, next(iter(near)))]
        while heap:
            w, v = heapq.heappop(heap)
            if v in seen or -w != weight[v]:
                continue
            seen.add(v)
            for x, n in near[v].items():
                if x not in seen:
                    weight[x] += n
                    heapq.heappush(heap, (-weight[x], x))
                    if weight[x] >= best:
                        root[find(x)] = find(v)
        if len(seen) < len(near):
            return 0  # not connected
        merged: dict[int, dict[int, int]] = {find(v): {} for v in near}
        for v, of in near.items():
            into = merged[find(v)]
            for x, n in of.items():
                if find(x) != find(v):
                    into[find(x)] = into.get(find(x), 0) + n
        near = merged
    return best


def min_cut(certificate: DataFrame, vertices: DataFrame, k: int) -> int:
    """min(w, k) of the global minimum cut; the certificate has at most k (V - 1) edges.

    Beyond MIN_CUT_VERTICES only what is exact is answered (not connected, or k = 1); else it raises.
    """
    named = vertices.select("vertex").distinct()
    n = named.count()
    if n <= MIN_CUT_VERTICES:
        rows = ((r.u, r.v) for r in certificate.select("u", "v").toLocalIterator())
        return least_cut_to(k, rows, [r.vertex for r in named.toLocalIterator()])
    found = star_components(certificate.select("u", "v"))[0]
    components = named.join(found, "vertex", "left").agg(F.countDistinct(F.coalesce("component", "vertex")).alias("n")).first().n
    if components > 1:
        return 0
    if k <= 1:
        return k
    raise ValueError(f"a minimum cut up to {k} of {n} vertices is not searched beyond {MIN_CUT_VERTICES}")


def is_edge_connected(certificate: DataFrame, vertices: DataFrame, j: int) -> bool:
    return min_cut(certificate, vertices, j) >= j


def bridges(certificate: DataFrame) -> list[tuple[int, int]]:
    """Edges whose loss parts a component, from a certificate of k >= 2, by depth-first low points on the driver.

    A certificate of more than ``BRIDGE_EDGES`` edges raises.
    """
    if certificate.count() > BRIDGE_EDGES:
        raise ValueError(f"bridges are not searched in a certificate of more than {BRIDGE_EDGES} edges")
    rows = sorted((r.u, r.v) for r in certificate.select("u", "v").toLocalIterator())
    near: dict[int, list[int]] = {}
    for u, v in rows:
        near.setdefault(u, []).append(v)
        near.setdefault(v, []).append(u)
    depth: dict[int, int] = {}
    low: dict[int, int] = {}
    out = []
    for root in near:
        if root in depth:
            continue
        depth[root] = low[root] = 0
        stack = [(root, None, iter(near[root]))]
        while stack:
            v, parent, it = stack[-1]
            for x in it:
                if x == parent:
                    continue
                if x in depth:
                    low[v] = min(low[v], depth[x])
                else:
                    depth[x] = low[x] = depth[v] + 1
                    stack.append((x, v, iter(near[x])))
                    break
            else:
                stack.pop()
                if stack:
                    up = stack[-1][0]
                    low[up] = min(low[up], low[v])
                    if low[v] > depth[up]:
                        out.append((min(up, v), max(up, v)))
    return sorted(out)
