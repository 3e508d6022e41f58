"""Connected components of link tables."""

from __future__ import annotations

from pyspark.sql import DataFrame

from edgesketch.tables import star_components


def connected(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of (a, b) links; root is the least node it is connected with."""
    stars, _ = star_components(edges.select("a", "b").toDF("u", "v"))
    return stars.toDF("node", "root")
