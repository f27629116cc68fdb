"""The searches that the index is compared with, each over a batch of queries."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathmeet.operators.frontier import levels, relaxed
from pathmeet.operators.graph import Graph
from pathmeet.scratch import bucketed, staged


def single_source(g: Graph, sources: DataFrame) -> DataFrame:
    """(s, v, d, parent) of complete searches from ``sources`` (id)."""
    start = sources.select(F.col("id").alias("s"), F.col("id").alias("v"), F.lit(None).cast("long").alias("parent"))
    if g.weighted:
        return weighted_sssp(g, sources)
    return levels(g.arcs, start, keys=("s",), carry={"parent": F.min("v")})


def weighted_sssp(g: Graph, sources: DataFrame) -> DataFrame:
    """(s, v, d, parent) by label correction, to the fixpoint."""
    zero = F.lit(0).cast(g.arcs.schema["w"].dataType)
    start = sources.select(F.col("id").alias("s"), F.col("id").alias("v"), zero.alias("d"), F.lit(None).cast("long").alias("parent"), F.lit(None).cast("long").alias("r"))
    return relaxed(g.arcs, start, keys=("s",), tie="parent").drop("r")


def all_pairs(g: Graph, most_nodes: int = 5000) -> DataFrame:
    """(s, v, d) of all pairs; refused on graphs where n squared rows are out of reach."""
    if g.n > most_nodes:
        raise ValueError(f"{g.n} nodes: all pairs are stored for up to {most_nodes}")
    return single_source(g, g.nodes.select("id")).select("s", "v", "d")


def bfs_distance(g: Graph, queries: DataFrame) -> DataFrame:
    """(qid, s, t, dist, scanned): one search per distinct source, which ends once it has reached all of its targets.

    ``scanned`` counts the arcs that the search of the query alone reads: those of all levels before the target's."""
    nodes = g.nodes.select("id")
    known = queries.join(nodes.select(F.col("id").alias("s")), "s", "left_semi").join(nodes.select(F.col("id").alias("t")), "t", "left_semi")
    wanted = staged(known.select("s", F.col("t").alias("v")).distinct(), "bfs-wanted")
    degree = g.nodes.select(F.col("id").alias("v"), "deg")
    hits, loads, left = [], [], [wanted]

    def note(level: DataFrame) -> DataFrame:
        """Keeps what the level tells, and the rows of sources that still miss a target."""
        level = staged(level, "bfs-level")
        found = staged(level.join(wanted, ["s", "v"], "left_semi").select("s", "v", "d"), "bfs-hits")
        hits.append(found)
        loads.append(staged(level.join(degree, "v").groupBy("s", "d").agg(F.sum("deg").alias("load")), "bfs-loads"))
        left[0] = staged(left[0].join(found, ["s", "v"], "left_anti"), "bfs-left")
        return level.join(left[0].select("s").distinct(), "s", "left_semi")

    first = wanted.select("s").distinct().select("s", F.col("s").alias("v"))
    start = note(first.withColumn("d", F.lit(0).cast("long"))).select("s", "v")
    levels(g.arcs, start, keys=("s",), after=lambda level, _: note(level))
    dist = reduce(DataFrame.unionByName, hits).withColumnRenamed("v", "t").withColumnRenamed("d", "dist")
    answered = known.join(dist, ["s", "t"], "left")
    load = reduce(DataFrame.unionByName, loads)
    upto = F.coalesce(F.sum("load").over(Window.partitionBy("s").orderBy("d").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    before = load.select("s", F.col("d").alias("dist"), upto.alias("read"))
    whole = load.groupBy("s").agg(F.sum("load").alias("all"))
    work = answered.join(before, ["s", "dist"], "left").join(whole, "s").select("qid", "dist", F.when(F.col("dist").isNull(), F.col("all")).otherwise(F.col("read")).alias("scanned"))
    return queries.join(work, "qid", "left").select("qid", "s", "t", "dist", F.coalesce("scanned", F.lit(0)).alias("scanned"))


def bidirectional_bfs(g: Graph, queries: DataFrame, seeds: DataFrame | None = None) -> DataFrame:
    """(qid, s, t, dist, scanned): two searches per query, the one with fewer arcs to read goes on.

    A query ends when the sum of the finished depths reaches the best meeting, or a side is
    exhausted. Levels are written once each, and only the last one of a side is expanded. ``seeds`` (qid, side, v, d, depth) starts sides from known levels instead of
    their endpoint: all nodes up to ``depth`` are given."""
    ends = queries.select("qid", F.explode(F.array(F.struct(F.lit(0).alias("side"), F.col("s").alias("v")), F.struct(F.lit(1).alias("side"), F.col("t").alias("v")))).alias("e"))
    plain = ends.select("qid", "e.side", "e.v", F.lit(0).cast("long").alias("d"), F.lit(0).cast("long").alias("depth")).join(g.nodes.select(F.col("id").alias("v")), "v", "left_semi")
    start = plain if seeds is None else seeds.select("qid", "side", "v", "d", "depth")
    levels_held = [staged(start, "bidi-level")]
    visited = levels_held[0]
    control = staged(
        queries.select("qid", F.explode(F.array(F.lit(0), F.lit(1))).alias("side")).join(visited.groupBy("qid", "side").agg(F.max("depth").alias("depth")), ["qid", "side"], "left")
        .select("qid", "side", F.coalesce("depth", F.lit(0).cast("long")).alias("depth"), F.lit(0).cast("long").alias("scanned")),
        "bidi-control",
    )
    best = staged(_meetings(visited, visited), "bidi-best")
    degree = g.nodes.select(F.col("id").alias("v"), "deg")
    front = staged(visited.join(control.select("qid", "side", F.col("depth").alias("at")), ["qid", "side"]).where("d = at").drop("at"), "bidi-front")
    while True:
        load = front.join(degree, "v").groupBy("qid", "side").agg(F.sum("deg").alias("load"))
        facts = control.join(load, ["qid", "side"], "left").groupBy("qid").agg(
            F.sum("depth").alias("reach"), F.min(F.struct("load", "side")).alias("least"), F.count("load").alias("sides")
        )
        # a side whose last level is empty cannot grow: the query ends
        going = facts.where("sides = 2").join(best, "qid", "left").where(F.col("best").isNull() | (F.col("reach") < F.col("best")))
        turn = staged(going.select("qid", F.col("least.side").alias("side"), F.col("least.load").alias("load")), "bidi-turn")
        if turn.isEmpty():
            break
        grown = front.join(turn, ["qid", "side"], "left_semi").join(g.arcs.select(F.col("src").alias("v"), "dst"), "v")
        new = grown.select("qid", "side", F.col("dst").alias("v"), (F.col("d") + 1).alias("d")).distinct()
        new = staged(new.join(visited.select("qid", "side", "v"), ["qid", "side", "v"], "left_anti").withColumn("depth", F.col("d")), "bidi-new")
        met = _meetings(new, visited)
        best = staged(best.unionByName(met).groupBy("qid").agg(F.min("best").alias("best")), "bidi-best")
        levels_held.append(new)
        visited = reduce(DataFrame.unionByName, levels_held)
        live = going.select("qid")
        front = staged(front.join(turn, ["qid", "side"], "left_anti").join(live, "qid", "left_semi").unionByName(new), "bidi-front")
        step = turn.withColumn("one", F.lit(1))
        control = staged(
            control.join(step, ["qid", "side"], "left").select("qid", "side", (F.col("depth") + F.coalesce("one", F.lit(0))).alias("depth"), (F.col("scanned") + F.coalesce("load", F.lit(0))).alias("scanned")), "bidi-control"
        )
    work = control.groupBy("qid").agg(F.sum("scanned").alias("scanned"))
    return queries.join(best, "qid", "left").join(work, "qid", "left").select("qid", "s", "t", F.col("best").alias("dist"), F.coalesce("scanned", F.lit(0)).alias("scanned"))


def _meetings(some: DataFrame, all_rows: DataFrame) -> DataFrame:
    one = some.select("qid", "side", "v", F.col("d").alias("d1"))
    other = all_rows.select("qid", (1 - F.col("side")).alias("side"), "v", F.col("d").alias("d2"))
    return one.join(other, ["qid", "side", "v"]).groupBy("qid").agg(F.min(F.col("d1") + F.col("d2")).alias("best"))


def bidirectional_weighted(g: Graph, queries: DataFrame) -> DataFrame:
    """(qid, s, t, dist): two label-correcting searches per query, each cut at half of the best upper bound.

    Every shortest path has a node with both parts at most half plus one arc away, so arcs
    that cross the two settled sides are tried as well."""
    ends = queries.select("qid", F.explode(F.array(F.struct(F.lit(0).alias("side"), F.col("s").alias("v")), F.struct(F.lit(1).alias("side"), F.col("t").alias("v")))).alias("e"))
    zero = F.lit(0).cast(g.arcs.schema["w"].dataType)
    start = ends.select("qid", "e.side", "e.v", zero.alias("d"), F.lit(None).cast("long").alias("parent")).join(g.nodes.select(F.col("id").alias("v")), "v", "left_semi")
    hops = levels(g.arcs, queries.select("qid", F.col("s").alias("v"), zero.alias("w")), keys=("qid",), carry={"w": F.min("w")})
    reached = hops.join(queries.select("qid", F.col("t").alias("v")), ["qid", "v"]).select("qid", "d")
    heaviest = g.arcs.agg(F.max("w")).first()[0] or 0
    bound = staged(reached.select("qid", (F.col("d") * heaviest).alias("r")), "bidi-bound")
    labels = relaxed(g.arcs, start.join(bound, "qid"), keys=("qid", "side"), tie="parent", may_expand=F.col("d") * 2 <= F.col("r"))
    labels = staged(labels.select("qid", "side", "v", "d"), "bidi-labels")
    met = _meetings(labels, labels)
    return queries.join(met, "qid", "left").select("qid", "s", "t", F.col("best").alias("dist"))


def astar(g: Graph, queries: DataFrame, tables: DataFrame, landmarks: int = 16, slack: int | None = 0) -> DataFrame:
    """(qid, s, t, dist, scanned): goal-directed search with triangle bounds from anchor tables as potentials.

    ``tables`` (a, v, d) of the ``landmarks`` least anchors serve. A round opens, for every query
    at once, the labels whose length plus bound is within ``slack`` of the query's least (None: all
    that can still improve the answer, in fewer rounds and with more arcs read). A label is dropped
    once its bound reaches the best path known, the first of which leads through a landmark."""
    chosen = F.broadcast(tables.select("a").distinct().orderBy("a").limit(landmarks))
    spots = tables.join(chosen, "a", "left_semi").groupBy("v").agg(F.transform(F.sort_array(F.collect_list(F.struct("a", "d"))), lambda x: x["d"]).alias("spots"))
    spots = bucketed(spots, "spots", "v")
    kind = g.arcs.schema["w"].dataType
    comps = g.components
    known = queries.select("qid", "s", "t").join(comps.select(F.col("id").alias("s"), F.col("comp").alias("cs")), "s").join(comps.select(F.col("id").alias("t"), F.col("comp").alias("ct")), "t").where("cs = ct")
    known = known.join(spots.select(F.col("v").alias("s"), F.col("spots").alias("near")), "s", "left").join(spots.select(F.col("v").alias("t"), F.col("spots").alias("goal")), "t", "left")
    detour = F.array_min(F.zip_with("near", "goal", lambda x, y: x + y)).cast(kind)
    goals = staged(known.select("qid", "s", "t", "goal", F.when(F.col("s") == F.col("t"), F.lit(0).cast(kind)).otherwise(detour).alias("best")), "astar-goals")
    targets = goals.select("qid", F.col("t").alias("v"))

    def valued(rows: DataFrame) -> DataFrame:
        ahead = F.coalesce(F.array_max(F.zip_with("spots", "goal", lambda x, y: F.abs(x - y))), F.lit(0)).cast(kind)
        return rows.join(spots, "v", "left").join(goals.select("qid", "goal"), "qid").select("qid", "v", "d", (F.col("d") + ahead).alias("f"))

    labels = staged(goals.select("qid", F.col("s").alias("v"), F.lit(0).cast(kind).alias("d")), "astar-labels")
    waiting, best, read = valued(labels), goals.select("qid", "best"), []
    while True:
        alive = waiting.join(best, "qid").where("best is null or f < best").drop("best")
        now = F.lit(True) if slack is None else F.col("f") <= F.col("least") + slack
        held = staged(alive.join(alive.groupBy("qid").agg(F.min("f").alias("least")), "qid").select("qid", "v", "d", "f", now.alias("now")), "astar-held")
        if held.isEmpty():
            break
        turn = held.where("now")
        read.append(turn.select("qid", "v"))
        reached = turn.join(g.arcs.select(F.col("src").alias("v"), "dst", "w"), "v").groupBy("qid", F.col("dst").alias("v")).agg(F.min(F.col("d") + F.col("w")).alias("d"))
        lower = reached.join(labels.select("qid", "v", F.col("d").alias("old")), ["qid", "v"], "left").where("old is null or d < old").drop("old")
        better = staged(valued(lower), "astar-better")
        labels = staged(labels.unionByName(better.select("qid", "v", "d")).groupBy("qid", "v").agg(F.min("d").alias("d")), "astar-labels")
        hits = better.join(targets, ["qid", "v"], "left_semi").select("qid", F.col("d").alias("best"))
        best = staged(best.unionByName(hits).groupBy("qid").agg(F.min("best").alias("best")), "astar-best")
        waiting = held.where("not now").drop("now").join(better.select("qid", "v"), ["qid", "v"], "left_anti").unionByName(better)
    opened = read[0] if read else targets.limit(0)
    for more in read[1:]:
        opened = opened.unionByName(more)
    work = opened.join(g.nodes.select(F.col("id").alias("v"), "deg"), "v").groupBy("qid").agg(F.sum("deg").alias("scanned"))
    return queries.join(best, "qid", "left").join(work, "qid", "left").select("qid", "s", "t", F.col("best").alias("dist"), F.coalesce("scanned", F.lit(0)).alias("scanned"))


def landmark_estimate(tables: DataFrame, queries: DataFrame, k: int | None = None) -> DataFrame:
    """(qid, s, t, dist): the least detour d(s, a) + d(a, t) over the ``k`` least anchors (all by default)."""
    used = tables if k is None else tables.join(F.broadcast(tables.select("a").distinct().orderBy("a").limit(k)), "a", "left_semi")
    one = used.select("a", F.col("v").alias("s"), F.col("d").alias("d1"))
    two = used.select("a", F.col("v").alias("t"), F.col("d").alias("d2"))
    best = queries.join(one, "s").join(two, ["a", "t"]).groupBy("qid").agg(F.min(F.col("d1") + F.col("d2")).alias("dist"))
    return queries.join(best, "qid", "left").select("qid", "s", "t", "dist")
