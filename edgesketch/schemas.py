"""The fixed schemas of the engine, as DDL strings, and the packing of edge ids."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

UPDATES = "seq long, u long, v long, delta tinyint, ts timestamp"
EDGES = "u long, v long"
BUCKETS = "copy int, vertex long, sampler int, col int, level int, xe long, xc long"
LABELS = "vertex long, component long"
FOREST = "u long, v long, round int"
PAIRS = "pair_id long, u long, v long"
CUTS = "cut_id long, vertex long"


def edge_id(u: Column, v: Column) -> Column:
    """``(lo << 32) | hi``: the xor of ids is the xor of both halves, so a lone id unpacks."""
    return F.shiftleft(F.least(u, v), 32).bitwiseOR(F.greatest(u, v))


def endpoints_of(eid: Column) -> tuple[Column, Column]:
    return F.shiftright(eid, 32), eid.bitwiseAND(F.lit(0xFFFFFFFF))
