"""Distance of every node to its nearest anchor: one multi-source search."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.operators.frontier import levels, relaxed
from pathmeet.operators.graph import Graph
from pathmeet.scratch import bucketed


def radii(g: Graph, anchors: DataFrame) -> DataFrame:
    """(u, r, anchor): distance to the nearest anchor and the least id of those at that distance.

    Nodes of components without anchors have null in both."""
    start = anchors.select(F.col("id").alias("v"), F.col("id").alias("anchor"))
    if g.weighted:
        zero = F.lit(0).cast(g.arcs.schema["w"].dataType)
        found = relaxed(g.arcs, start.select("v", zero.alias("d"), "anchor", F.lit(None).cast("long").alias("r")), keys=(), tie="anchor")
    else:
        found = levels(g.arcs, start, keys=(), carry={"anchor": F.min("anchor")})
    known = g.nodes.select(F.col("id").alias("u")).join(found.select(F.col("v").alias("u"), F.col("d").alias("r"), "anchor"), "u", "left")
    return bucketed(known, "radius", "u", rows=g.n)
