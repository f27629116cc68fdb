"""Paths of answered queries: a leg from each endpoint to the witness, unrolled and joined."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.operators.graph import Graph
from pathmeet.operators.index import Index
from pathmeet.operators.vicinity import anchor_tables, inner_arcs, vicinities
from pathmeet.scratch import drop_path, made, paths_of, staged


def legs(answers: DataFrame) -> DataFrame:
    """(qid, side, table, owner, node): which table of which owner holds the way to ``node``.

    Side 0 starts at s, side 1 at t; anchor cases and memberships have one leg."""
    answered = answers.where("dist is not null and witness is not null")
    one = lambda case, side, table, owner, node: F.when(F.col("case") == case, F.array(F.struct(F.lit(side).alias("side"), F.lit(table).alias("table"), F.col(owner).alias("owner"), F.col(node).alias("node"))))
    both = F.array(*(F.struct(F.lit(i).alias("side"), F.lit("vicinity").alias("table"), F.col(o).alias("owner"), F.col("witness").alias("node")) for i, o in enumerate(("s", "t"))))
    which = F.coalesce(
        one("same", 0, "vicinity", "s", "s"), one("source_anchor", 0, "anchor", "s", "t"), one("target_anchor", 1, "anchor", "t", "s"),
        one("target_in_source", 0, "vicinity", "s", "t"), one("source_in_target", 1, "vicinity", "t", "s"), F.when(F.col("case") == "meet", both),
    )
    return answered.select("qid", F.explode(which).alias("e")).select("qid", "e.*")


def unroll_parent(index: Index, parts: DataFrame, tables: DataFrame) -> DataFrame:
    """(qid, side, step, node): the nodes of each leg, by parents from its far end; step counts from the owner."""
    known = index.vicinity.select(F.lit("vicinity").alias("table"), F.col("u").alias("owner"), F.col("v").alias("node"), "parent", "d")
    known = known.unionByName(tables.select(F.lit("anchor").alias("table"), F.col("a").alias("owner"), F.col("v").alias("node"), "parent", "d"))
    owners = parts.select("table", "owner").distinct()
    known = staged(known.join(owners, ["table", "owner"], "left_semi"), "route-known")
    current = staged(parts.join(known, ["table", "owner", "node"]), "route-step")
    steps = [current]
    while True:
        up = current.where("parent is not null").select("qid", "side", "table", "owner", F.col("parent").alias("node"))
        current = staged(up.join(known, ["table", "owner", "node"]), "route-step")
        if current.isEmpty():
            break
        steps.append(current)
    out = steps[0]
    for more in steps[1:]:
        out = out.unionByName(more)
    return out.select("qid", "side", F.col("d").alias("at"), "node")


def follow_hops(index: Index, parts: DataFrame) -> DataFrame:
    """(qid, side, at, node): the nodes of vicinity legs by stored first steps, through one node's table after another.

    After a step the target is in the vicinity of the new node again, or equals it. Tables of nodes that
    the index lacks are built when a step leads there, and deleted after it, so an index of the endpoints is enough."""
    g, first, inner = index.graph, index.vicinity, None
    current = staged(parts.select("qid", "side", "node", F.col("owner").alias("here"), F.lit(0).cast("long").alias("at")), "hop-step")
    steps = [current]
    while True:
        open_rows = current.where("here <> node")
        owners = open_rows.select(F.col("here").alias("u")).distinct()
        lacking = staged(owners.join(first.select("u"), "u", "left_anti"), "hop-owners")
        before, held = made(), first
        if not lacking.isEmpty():
            inner = inner if inner is not None or g.weighted else inner_arcs(g, index.radius)
            before = made()
            held = first.unionByName(vicinities(g, index.radius, lacking.select(F.col("u").alias("id")), inner=inner))
        hops = held.select(F.col("u").alias("here"), F.col("v").alias("node"), "next_hop")
        onward = open_rows.join(hops, ["here", "node"]).select("qid", "side", "node", F.col("next_hop").alias("here"), (F.col("at") + 1).alias("at"))
        current = staged(onward, "hop-step")
        for path in made() - before - paths_of(current):
            drop_path(current.sparkSession, path)
        if current.isEmpty():
            break
        steps.append(current)
    out = steps[0]
    for more in steps[1:]:
        out = out.unionByName(more)
    return out.select("qid", "side", "at", F.col("here").alias("node"))


def paths(index: Index, answers: DataFrame, via: str = "parent") -> DataFrame:
    """(qid, path): one shortest path per answered query, from s to t.

    ``via='next_hop'`` follows stored first steps for vicinity legs; legs of anchors always
    unroll the anchor's table."""
    parts = staged(legs(answers), "legs")
    at_anchor = parts.where("table = 'anchor'")
    tables = index.tables if index.tables is not None else anchor_tables(index.graph, index.anchors, at_anchor.select(F.col("owner").alias("id")).distinct())
    if via == "parent":
        nodes = unroll_parent(index, parts, tables)
    else:
        nodes = unroll_parent(index, at_anchor, tables).unionByName(follow_hops(index, parts.where("table = 'vicinity'")))
    place = F.when(F.col("side") == 0, F.col("at")).otherwise(-F.col("at"))
    rows = nodes.select("qid", "side", F.struct(F.col("side"), place.alias("place"), F.col("node").alias("node")).alias("x"))
    ordered = rows.groupBy("qid").agg(F.transform(F.sort_array(F.collect_list("x")), lambda x: x["node"]).alias("raw"))
    # the two legs meet in the witness, which both hold
    merged = F.filter("raw", lambda x, i: (i == 0) | (x != F.try_element_at("raw", i.cast("int"))))
    return ordered.select("qid", merged.alias("path"))


def path_steps(found: DataFrame) -> DataFrame:
    """(qid, pos, node): paths as rows."""
    return found.select("qid", F.posexplode("path").alias("pos", "node"))


def validate_paths(g: Graph, found: DataFrame, answers: DataFrame) -> DataFrame:
    """(qid, valid): every step is an arc, the ends are s and t, and the length is the distance."""
    pairs = found.select("qid", F.posexplode(F.arrays_zip(F.slice("path", 1, F.greatest(F.size("path") - 1, F.lit(0))).alias("src"), F.expr("slice(path, 2, greatest(size(path) - 1, 0))").alias("dst"))).alias("pos", "p"))
    length = pairs.select("qid", "p.src", "p.dst").join(g.arcs, ["src", "dst"], "left").groupBy("qid").agg(F.sum("w").alias("length"), F.count_if(F.col("w").isNull()).alias("bad"))
    ends = found.select("qid", F.element_at("path", 1).alias("first"), F.element_at("path", -1).alias("last"))
    joined = answers.select("qid", "s", "t", "dist").join(ends, "qid").join(length, "qid", "left")
    ok = (F.col("first") == F.col("s")) & (F.col("last") == F.col("t")) & (F.coalesce("bad", F.lit(0)) == 0) & (F.coalesce("length", F.lit(0)) == F.col("dist"))
    return joined.select("qid", ok.alias("valid"))
