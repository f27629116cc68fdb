"""Keeping an index up to date as edges arrive, without building it anew.

A new edge can change the vicinity of u only if one of its ends lies in the open ball of u:
a path that uses the edge reaches that end first, along old edges. The same holds for
the radius of u. Boundary flags also change where an end is a member. Anchors stay."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.operators.frontier import relaxed
from pathmeet.operators.graph import Graph, simple_edges
from pathmeet.operators.index import Index
from pathmeet.operators.vicinity import boundaries, vicinities
from pathmeet.scratch import bucketed, staged


def add_edges(index: Index, edges: DataFrame, whole: bool = True) -> Index:
    """The index of the graph with ``edges`` (src, dst) added; only what can change is built again.

    ``whole`` says that the index covers all nodes, so that nodes first seen here get a vicinity
    as well. Known edges, loops and nulls change nothing. Unweighted graphs only. Anchor tables
    are left to be built on demand."""
    g = index.graph
    if g.weighted:
        raise ValueError("repair is for unweighted graphs")
    known = g.arcs.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    fresh = staged(simple_edges(edges).join(known, ["a", "b"], "left_anti"), "repair-edges")
    added = fresh.count()
    if not added:
        return index
    both = fresh.select(F.col("a").alias("src"), F.col("b").alias("dst"), "w").union(fresh.select("b", "a", "w"))
    gain = staged(both.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("more")), "repair-ends")
    ends = gain.select(F.col("id").alias("v"))
    arcs = bucketed(g.arcs.unionByName(both), "graph_arcs", "src")
    nodes = bucketed(g.nodes.join(gain, "id", "full").select("id", (F.coalesce("deg", F.lit(0)) + F.coalesce("more", F.lit(0))).alias("deg")), "graph_nodes", "id")
    grown = Graph(nodes, arcs, nodes.count(), g.m + added)

    labels = index.radius.where("r is not null").select(F.col("u").alias("v"), F.col("r").alias("d"), "anchor", F.lit(None).cast("long").alias("r"))
    reached = relaxed(arcs, labels, keys=(), tie="anchor", opened=ends)
    radius = bucketed(nodes.select(F.col("id").alias("u")).join(reached.select(F.col("v").alias("u"), F.col("d").alias("r"), "anchor"), "u", "left"), "radius", "u")

    stale = index.vicinity.where("inside").join(ends, "v", "left_semi").select(F.col("u").alias("id"))
    if whole:
        stale = stale.union(gain.join(g.nodes, "id", "left_anti").select("id"))
    stale = staged(stale.distinct(), "repair-stale")
    rebuilt = vicinities(grown, radius, sources=stale)
    kept = index.vicinity.join(stale.select(F.col("id").alias("u")), "u", "left_anti")
    vicinity = bucketed(kept.unionByName(rebuilt), "vicinity", "u")
    touched = staged(vicinity.join(ends, "v", "left_semi").select("u").union(stale.select(F.col("id").alias("u"))).distinct(), "repair-touched")
    flags = boundaries(grown, vicinity.join(touched, "u", "left_semi"), radius)
    boundary = bucketed(index.boundary.join(touched, "u", "left_anti").unionByName(flags), "boundary", "u")
    return Index(grown, index.anchors, radius, vicinity, boundary)
