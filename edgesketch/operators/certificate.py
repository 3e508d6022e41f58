"""k-connectivity certificates: k edge-disjoint forests, the i-th peeled from copy i of the sketch."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.functions.sampler import SketchParams
from edgesketch.operators.batching import BatchPolicy
from edgesketch.operators.forest import spanning_forest
from edgesketch.operators.sketch import GraphSketch
from edgesketch.tables import materialize


def sketch(updates: DataFrame, params: SketchParams, k: int, policy: BatchPolicy = BatchPolicy()) -> GraphSketch:
    """k copies in one pass: batches are k times as large, hashes of the copies independent."""
    return GraphSketch.build(updates, params.with_(copies=k), policy)


def peeled(graph: GraphSketch, k: int | None = None, vertices: DataFrame | None = None) -> Iterator[tuple[DataFrame, bool]]:
    """((u, v, forest_no) of one forest, complete) after another: forest i spans what is left after the forests before it.

    Removing a forest is linear: its edges, sketched under copy i, are xored in as that copy is read. Copy i
    does not depend on how many copies there are, so the first k forests are those of a certificate of k.
    """
    k = k or graph.params.copies
    if k > graph.params.copies:
        raise ValueError("a certificate of k forests takes k copies")
    made = None
    for i in range(k):
        remove = None
        if made is not None:
            remove = GraphSketch.build(made.select("u", "v"), graph.params.copy(i), BatchPolicy("raw"))
        found = spanning_forest(graph, vertices=vertices, copy=i, remove=remove)
        forest = materialize(found.forest.select("u", "v", F.lit(i).alias("forest_no")), "forest")
        yield forest, found.complete
        if forest.isEmpty():
            break  # nothing is left: the certificate is the whole graph
        made = forest if made is None else made.unionByName(forest)


def peel(graph: GraphSketch, k: int | None = None, vertices: DataFrame | None = None) -> tuple[DataFrame, bool]:
    """((u, v, forest_no), complete) of all k forests."""
    made, complete = None, True
    for forest, ok in peeled(graph, k, vertices):
        complete &= ok
        made = forest if made is None else made.unionByName(forest)
    return made, complete
