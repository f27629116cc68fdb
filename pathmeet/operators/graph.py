"""The graph relation: simple, undirected, both directions stored, bucketed by source."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.components import component_labels
from pathmeet.scratch import bucketed, settled, staged


@dataclass
class Graph:
    """``nodes`` (id, deg), ``arcs`` (src, dst, w) in both directions, and the two sizes."""

    nodes: DataFrame
    arcs: DataFrame
    n: int
    m: int
    weighted: bool = False
    directed_links: int | None = None
    memo: dict = field(default_factory=dict, repr=False)

    @cached_property
    def components(self) -> DataFrame:
        """(id, comp): the least id of each node's component."""
        return component_labels(self.arcs.where("src < dst"))

    def reversed(self) -> DataFrame:
        return self.arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")


def simple_edges(edges: DataFrame, src: str = "src", dst: str = "dst", weight: str | None = None, combine: str = "min") -> DataFrame:
    """(a, b, w) with a < b: loops and nulls dropped, parallel edges merged.

    Raises if a weight is negative, null or not a number (checked in the same pass)."""
    w = F.col(weight) if weight else F.lit(1).cast("long")
    rows = edges.select(F.least(src, dst).cast("long").alias("a"), F.greatest(src, dst).cast("long").alias("b"), w.alias("w"), F.col(src).alias("s"), F.col(dst).alias("t"))
    rows = rows.where(F.col("s").isNotNull() & F.col("t").isNotNull() & (F.col("a") < F.col("b")))
    if weight:
        bad = F.col("w").isNull() | (F.col("w") < 0) | F.isnan(F.col("w").cast("double"))
        rows = rows.withColumn("w", F.when(bad, F.raise_error(F.lit("weights must be numbers of at least 0")).cast(rows.schema["w"].dataType)).otherwise(F.col("w")))
    return rows.groupBy("a", "b").agg({"min": F.min, "max": F.max, "sum": F.sum}[combine]("w").alias("w"))


def build_graph(edges: DataFrame, src: str = "src", dst: str = "dst", weight: str | None = None, combine: str = "min", directed_input: bool = False) -> Graph:
    """Normalises raw edges. With ``directed_input``, the distinct ordered pairs as recorded are counted too."""
    pairs = staged(simple_edges(edges, src, dst, weight, combine), "graph-edges")
    m = pairs.count()
    arcs = bucketed(pairs.select(F.col("a").alias("src"), F.col("b").alias("dst"), "w").union(pairs.select("b", "a", "w")), "graph_arcs", "src", rows=2 * m)
    nodes = bucketed(arcs.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg")), "graph_nodes", "id", rows=2 * m)
    n = nodes.count()
    recorded = edges.where((F.col(src) != F.col(dst))).select(src, dst).distinct().count() if directed_input else None
    return Graph(nodes, arcs, n, m, weight is not None, recorded)


def sizes(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """One row of raw edges: n, m, directed_links, mean_degree, max_degree of the graph they give, which is not built or written."""
    a, b = F.col(src).cast("long"), F.col(dst).cast("long")
    links = edges.select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b"), (a < b).alias("up")).where(a.isNotNull() & b.isNotNull() & (a != b))
    ways = F.max(F.col("up").cast("long")) + F.max((~F.col("up")).cast("long"))
    pairs = links.groupBy("a", "b").agg(ways.alias("ways"))
    # the first end of a link carries how many of its two directions were recorded
    ends = pairs.select(F.explode(F.array(F.struct(F.col("a").alias("id"), "ways"), F.struct(F.col("b").alias("id"), F.lit(0).cast("long").alias("ways")))).alias("e"))
    nodes = ends.groupBy("e.id").agg(F.count("*").alias("deg"), F.sum("e.ways").alias("ways"))
    return nodes.agg(
        F.count("*").alias("n"), F.expr("coalesce(sum(deg), 0L) div 2").alias("m"), F.coalesce(F.sum("ways"), F.lit(0)).cast("long").alias("directed_links"),
        F.round(F.avg("deg"), 6).alias("mean_degree"), F.max("deg").alias("max_degree"),
    )


def component_count(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """One row of raw edges: the number of components; a component is named by its least node. The labels are deleted when counted."""
    a, b = F.col(src).cast("long"), F.col(dst).cast("long")
    links = edges.select(a.alias("src"), b.alias("dst")).where(a.isNotNull() & b.isNotNull() & (a != b))
    return settled("component-count", lambda: component_labels(links).agg(F.count_if(F.col("id") == F.col("comp")).alias("components")))


def largest_component(g: Graph) -> Graph:
    """The subgraph of the component with most nodes (ties: the least label)."""
    sizes = g.components.groupBy("comp").agg(F.count("*").alias("size"))
    top = sizes.orderBy(F.desc("size"), "comp").limit(1)
    keep = g.components.join(F.broadcast(top), "comp", "left_semi").select("id")
    return induced(g, keep)


def induced(g: Graph, keep: DataFrame) -> Graph:
    """The subgraph on the nodes of ``keep`` (id)."""
    inside = g.arcs.join(keep.select(F.col("id").alias("src")), "src", "left_semi").join(keep.select(F.col("id").alias("dst")), "dst", "left_semi")
    return build_graph(inside.where("src < dst"), weight="w" if g.weighted else None)


def stats(g: Graph) -> DataFrame:
    """One row: nodes, links, degrees, components."""
    sizes = g.components.groupBy("comp").agg(F.count("*").alias("size")).agg(F.count("*").alias("components"), F.max("size").alias("largest"))
    degrees = g.nodes.agg(F.count("*").alias("n"), (F.sum("deg") / 2).cast("long").alias("m"), F.round(F.avg("deg"), 6).alias("mean_degree"), F.max("deg").alias("max_degree"))
    return degrees.join(F.broadcast(sizes))


def within_hops(g: Graph, sources: DataFrame, hops: int) -> DataFrame:
    """(u, v, d) of the nodes within ``hops`` of each source node (column ``id``)."""
    from pathmeet.operators.frontier import levels

    return levels(g.arcs, sources.select(F.col("id").alias("u"), F.col("id").alias("v")), stop=hops)


def common_neighbours(g: Graph, pairs: DataFrame) -> DataFrame:
    """(s, t, common) for pairs (s, t) of nodes."""
    mine = g.arcs.select(F.col("src").alias("s"), F.col("dst").alias("x"))
    theirs = g.arcs.select(F.col("src").alias("t"), F.col("dst").alias("x"))
    return pairs.select("s", "t").join(mine, "s").join(theirs, ["t", "x"]).groupBy("s", "t").agg(F.count("*").alias("common"))


def triangles(g: Graph) -> DataFrame:
    """(id, triangles) of the nodes in triangles."""
    from pathmeet.operators.triangles import triangle_counts

    return triangle_counts(g.arcs.where("src < dst"))


def k_core(g: Graph, k: int) -> DataFrame:
    """(id) of the nodes left after peeling those with fewer than ``k`` neighbours."""
    left = staged(g.nodes.where(F.col("deg") >= k).select("id"), "core")
    size = left.count()
    while True:
        inside = g.arcs.join(left.select(F.col("id").alias("src")), "src", "left_semi").join(left.select(F.col("id").alias("dst")), "dst", "left_semi")
        left = staged(inside.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg")).where(F.col("deg") >= k).select("id"), "core")
        now = left.count()
        if now == size:
            return left
        size = now
