"""Vicinities: the open ball of a node's radius and all neighbours of the ball."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.joins import bounded_join
from pathmeet.operators.frontier import levels, relaxed
from pathmeet.operators.graph import Graph
from pathmeet.scratch import bucketed, staged


def inner_arcs(g: Graph, radii: DataFrame) -> DataFrame:
    """The arcs that any ball expands: those not leaving an anchor, since no ball holds one.

    Nodes of high degree are anchors, so the join on these arcs has no hubs."""
    return bucketed(g.arcs.join(radii.where("r = 0").select(F.col("u").alias("src")), "src", "left_anti"), "inner_arcs", "src", rows=2 * g.m)


def vicinities(g: Graph, radii: DataFrame, sources: DataFrame | None = None, engine: str = "relational", exact_rim: bool = False, inner: DataFrame | None = None) -> DataFrame:
    """(u, v, d, parent, next_hop, inside) of all nodes, or of the ``sources`` (id) only.

    Every u has a self row; an anchor has no other. ``parent`` is the least member before v on a
    shortest path from u, ``next_hop`` the least first step. The kernel, for unweighted graphs that
    fit ``kernels.MOST_ARCS``, adds ``edge``, which marks the boundary. Weighted: labels inside the ball
    are exact, those on the rim are upper bounds unless ``exact_rim``."""
    start = radii.select("u", F.col("u").alias("v"), "r")
    if sources is not None:
        start = bounded_join(start, staged(sources.select(F.col("id").alias("u")).distinct(), "sources"), "u", "left_semi")
    if g.weighted:
        return _weighted(g, start, exact_rim)
    if engine == "kernel":
        from pathmeet.functions.kernels import kernel_vicinities

        spread = start.repartition(max(8, 4 * start.sparkSession.sparkContext.defaultParallelism), "u")
        return staged(kernel_vicinities(g, spread), "vicinity")
    arcs = inner if inner is not None else inner_arcs(g, radii)
    start = start.withColumn("parent", F.lit(None).cast("long")).withColumn("next_hop", F.lit(None).cast("long"))
    found = levels(
        arcs,
        start,
        carry={"r": F.first("r"), "parent": F.min("v"), "next_hop": F.min(F.coalesce("next_hop", "dst"))},
        may_expand=F.col("r").isNull() | (F.col("d") < F.col("r")),
    )
    inside = F.col("r").isNull() | (F.col("d") < F.col("r"))
    return bucketed(found.select("u", "v", "d", "parent", "next_hop", inside.alias("inside")), "vicinity", "u", rows=found.count())


def _weighted(g: Graph, start: DataFrame, exact_rim: bool) -> DataFrame:
    zero = F.lit(0).cast(g.arcs.schema["w"].dataType)
    rows = start.select("u", "v", zero.alias("d"), F.lit(None).cast("long").alias("parent"), "r")
    ball = F.col("r").isNull() | (F.col("d") < F.col("r"))
    found = relaxed(g.arcs, rows, keys=("u",), tie="parent", may_expand=ball)
    if exact_rim:
        full = relaxed(g.arcs, rows, keys=("u",), tie="parent")
        found = full.join(found.select("u", "v"), ["u", "v"], "left_semi")
    return bucketed(found.select("u", "v", "d", "parent", F.lit(None).cast("long").alias("next_hop"), ball.alias("inside")), "vicinity", "u")


def balls(vic: DataFrame) -> DataFrame:
    return vic.where("inside")


def rims(vic: DataFrame, radii: DataFrame) -> DataFrame:
    """(u, v, d): the members outside the ball, of nodes that are not anchors. A superset of the boundary."""
    return vic.where(~F.col("inside")).join(radii.where("r > 0").select("u"), "u", "left_semi").select("u", "v", "d")


def boundaries(g: Graph, vic: DataFrame, radii: DataFrame) -> DataFrame:
    """(u, v, d): rim members with a neighbour outside the vicinity.

    A member whose degree is at least the size of the vicinity has one for sure, so hubs are
    not enumerated; for the others the neighbours inside are counted against the degree. The
    kernel has looked at them while it held the vicinity, and marked those members."""
    if "edge" in vic.columns:
        return vic.where("edge").select("u", "v", "d")
    sizes = vic.groupBy("u").agg(F.count("*").alias("size"))
    rim = rims(vic, radii).join(g.nodes.select(F.col("id").alias("v"), "deg"), "v").join(sizes, "u")
    sure = rim.where("deg >= size").select("u", "v", "d")
    open_rows = rim.where("deg < size")
    around = open_rows.join(g.arcs.select(F.col("src").alias("v"), F.col("dst").alias("x")), "v")
    inside = around.join(vic.select("u", F.col("v").alias("x")), ["u", "x"], "left_semi").groupBy("u", "v").agg(F.count("*").alias("held"))
    counted = open_rows.join(inside, ["u", "v"], "left").where(F.coalesce("held", F.lit(0)) < F.col("deg")).select("u", "v", "d")
    return bucketed(sure.unionByName(counted), "boundary", "u", rows=vic.count())


def anchor_tables(g: Graph, anchors: DataFrame, only: DataFrame | None = None) -> DataFrame:
    """(a, v, d, parent): distances from anchors to all nodes; ``only`` (id) restricts the anchors.

    All anchors together give |L| n rows, more than the vicinities on dense graphs; batches
    need only the anchors among their endpoints."""
    from pathmeet.operators.baselines import single_source

    chosen = anchors.select("id") if only is None else anchors.select("id").join(only.select("id"), "id", "left_semi")
    return bucketed(single_source(g, chosen).withColumnRenamed("s", "a"), "anchor_dist", "a")


def pack(vic: DataFrame, bnd: DataFrame, radii: DataFrame, layout: str = "parent") -> DataFrame:
    """One row per node: sorted members and boundary as arrays. ``layout`` keeps parent, next_hop or neither."""
    extra = {"parent": ["parent"], "next_hop": ["next_hop"], "distance": []}[layout]
    members = vic.groupBy("u").agg(F.sort_array(F.collect_list(F.struct("v", "d", *extra))).alias("members"))
    edge = bnd.groupBy("u").agg(F.sort_array(F.collect_list(F.struct("v", "d"))).alias("boundary"))
    out = members.join(edge, "u", "left").join(radii, "u")
    return out.select("u", "r", "anchor", F.size("members").alias("size"), F.coalesce(F.size("boundary"), F.lit(0)).alias("boundary_size"), "members", F.coalesce("boundary", F.expr("array()").cast(edge.schema["boundary"].dataType)).alias("boundary"))
