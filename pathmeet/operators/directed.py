"""Directed graphs: a vicinity forward from the source, one backward from the target.

The forward radius of a node is its distance to the nearest anchor along the arcs, the
backward radius the distance from the nearest anchor. Forward and backward vicinity of a
pair share a node exactly if the distance is at most the sum of the two radii, and the least
sum over shared nodes is then the distance: the node of a shortest path at the forward radius
is a member of both, and members never understate."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.operators.anchors import draw_anchors
from pathmeet.operators.frontier import levels
from pathmeet.scratch import bucketed, staged


@dataclass
class DirectedGraph:
    """``nodes`` (id, deg: arcs in and out), ``out`` and ``back`` arcs (src, dst), and the two sizes."""

    nodes: DataFrame
    out: DataFrame
    back: DataFrame
    n: int
    m: int

    def along(self, direction: str) -> DataFrame:
        return {"out": self.out, "in": self.back}[direction]


def build_directed(edges: DataFrame, src: str = "src", dst: str = "dst") -> DirectedGraph:
    """Distinct arcs without loops and nulls, stored in both orders."""
    pairs = edges.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst")).where("src <> dst").distinct()
    out = bucketed(pairs, "arcs_out", "src")
    back = bucketed(out.select(F.col("dst").alias("src"), F.col("src").alias("dst")), "arcs_back", "src")
    ends = out.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("k")).unionByName(back.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("k")))
    nodes = bucketed(ends.groupBy("id").agg(F.sum("k").alias("deg")), "nodes_directed", "id")
    return DirectedGraph(nodes, out, back, nodes.count(), out.count())


def directed_radii(g: DirectedGraph, anchors: DataFrame, direction: str = "out") -> DataFrame:
    """(u, r, anchor): distance to (``out``) or from (``in``) the nearest anchor; null where there is none."""
    start = anchors.select(F.col("id").alias("v"), F.col("id").alias("anchor"))
    found = levels(g.along("in" if direction == "out" else "out"), start, keys=(), carry={"anchor": F.min("anchor")}, directed=True)
    known = g.nodes.select(F.col("id").alias("u")).join(found.select(F.col("v").alias("u"), F.col("d").alias("r"), "anchor"), "u", "left")
    return bucketed(known, f"radius_{direction}", "u")


def directed_vicinities(g: DirectedGraph, radii: DataFrame, direction: str = "out", sources: DataFrame | None = None) -> DataFrame:
    """(u, v, d, inside) forward or backward. A node without a radius gets all that it reaches."""
    start = radii.select("u", F.col("u").alias("v"), "r")
    if sources is not None:
        start = start.join(sources.select(F.col("id").alias("u")), "u", "left_semi")
    ball = F.col("r").isNull() | (F.col("d") < F.col("r"))
    inner = g.along(direction).join(radii.where("r = 0").select(F.col("u").alias("src")), "src", "left_anti")
    found = levels(bucketed(inner, f"inner_{direction}", "src"), start, carry={"r": F.first("r")}, may_expand=ball, directed=True)
    return bucketed(found.select("u", "v", "d", ball.alias("inside")), f"vicinity_{direction}", "u")


@dataclass
class DirectedIndex:
    graph: DirectedGraph
    anchors: DataFrame
    radius_out: DataFrame
    radius_in: DataFrame
    vicinity_out: DataFrame
    vicinity_in: DataFrame


def build_directed_index(g: DirectedGraph, alpha: float = 4.0, seed: int = 7, sources: DataFrame | None = None, targets: DataFrame | None = None, **draw) -> DirectedIndex:
    """Both radii of all nodes; vicinities of ``sources`` and ``targets`` (id), or of all nodes."""
    anchors = draw_anchors(g, alpha, seed, on_empty="whole", **draw)
    forward, backward = directed_radii(g, anchors, "out"), directed_radii(g, anchors, "in")
    return DirectedIndex(g, anchors, forward, backward, directed_vicinities(g, forward, "out", sources), directed_vicinities(g, backward, "in", targets))


def directed_distance(index: DirectedIndex, queries: DataFrame) -> DataFrame:
    """(qid, s, t, dist, case, probes, lower) of the distances from s to t.

    Cases in order: unknown_node, same, source_anchor, target_anchor, target_in_source,
    source_in_target, meet, unanswered. ``unreachable`` is stated where a table or a vicinity
    that holds everything within reach lacks the other end."""
    g = index.graph
    r_s = index.radius_out.select(F.col("u").alias("s"), F.col("r").alias("r_s"), F.lit(True).alias("has_s"))
    r_t = index.radius_in.select(F.col("u").alias("t"), F.col("r").alias("r_t"), F.lit(True).alias("has_t"))
    known = staged(queries.select("qid", "s", "t").join(r_s, "s", "left").join(r_t, "t", "left"), "directed-queries")
    open_rows = known.where("has_s and has_t and s <> t")

    def table(own: str, other: str, direction: str) -> DataFrame:
        at = open_rows.where(f"r_{own} = 0").select(F.col(own).alias("a")).distinct()
        reach = levels(g.along(direction), at.select("a", F.col("a").alias("v")), keys=("a",), directed=True)
        return reach.select(F.col("a").alias(own), F.col("v").alias(other), F.col("d").alias(f"table_{own}"))

    def held(own: str, other: str, vicinity: DataFrame) -> DataFrame:
        return vicinity.select(F.col("u").alias(own), F.col("v").alias(other), F.col("d").alias(f"in_{own}"))

    looked = open_rows.join(table("s", "t", "out"), ["s", "t"], "left").join(table("t", "s", "in"), ["s", "t"], "left")
    looked = looked.join(held("s", "t", index.vicinity_out), ["s", "t"], "left").join(held("t", "s", index.vicinity_in), ["s", "t"], "left")
    looked = staged(looked, "directed-looked")
    direct = F.coalesce("table_s", "table_t", "in_s", "in_t")
    rest = looked.where(direct.isNull() & (F.col("r_s") > 0) & (F.col("r_t") > 0)).select("qid", "s", "t")
    rim = index.vicinity_out.where("not inside").select(F.col("u").alias("s"), F.col("v").alias("x"), F.col("d").alias("d1"))
    other = index.vicinity_in.select(F.col("u").alias("t"), F.col("v").alias("x"), F.col("d").alias("d2"))
    met = rest.join(rim, "s").join(other, ["t", "x"], "left").groupBy("qid").agg(F.min(F.col("d1") + F.col("d2")).alias("met"), F.count("*").alias("probes"))
    facts = looked.drop("s", "t", "r_s", "r_t", "has_s", "has_t").join(met, "qid", "left")
    same = F.col("s") == F.col("t")
    whole = F.coalesce((F.col("r_s") == 0) | (F.col("r_t") == 0), F.lit(False)) | F.col("r_s").isNull() | F.col("r_t").isNull()
    dist = F.when(F.col("has_s").isNull() | F.col("has_t").isNull(), None).when(same, F.lit(0).cast("long")).otherwise(F.coalesce(direct, F.col("met")))
    case = (
        F.when(F.col("has_s").isNull() | F.col("has_t").isNull(), "unknown_node").when(same, "same")
        .when(F.col("table_s").isNotNull(), "source_anchor").when(F.col("table_t").isNotNull(), "target_anchor")
        .when(F.col("in_s").isNotNull(), "target_in_source").when(F.col("in_t").isNotNull(), "source_in_target")
        .when(F.col("met").isNotNull(), "meet").when(whole, "unreachable").otherwise("unanswered")
    )
    out = known.join(facts, "qid", "left")
    return out.select("qid", "s", "t", dist.alias("dist"), case.alias("case"), F.coalesce("probes", F.lit(0).cast("long")).alias("probes"), F.coalesce(dist, F.when(case == "unanswered", F.col("r_s") + F.col("r_t") + 1)).alias("lower"))
