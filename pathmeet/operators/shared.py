"""Searches that many sources share: a row holds a node and the set of sources that reach it, as bits.

A block of 1,024 sources is one row of 16 words, so a level of all of them is one join with the
arcs and one aggregation by bit_or, where a row per source and node would be 1,024 times as many."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathmeet.operators.frontier import MOST_ROUNDS
from pathmeet.operators.graph import Graph
from pathmeet.scratch import discard, staged

WORD, WORDS = 64, 16
BLOCK = WORD * WORDS
BITS = [f"w{i}" for i in range(WORDS)]


@contextmanager
def plainly_planned(spark: SparkSession) -> Iterator[None]:
    """Plans made and run inside infer no filters: a test of 16 computed words has 2^16 variants to the optimiser."""
    key = "spark.sql.constraintPropagation.enabled"
    before = spark.conf.get(key)
    spark.conf.set(key, "false")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def placed(sources: DataFrame) -> DataFrame:
    """(id, k): the place of each source (id), from 0."""
    return staged(sources.select("id").distinct().select("id", (F.row_number().over(Window.orderBy("id")) - 1).cast("long").alias("k")), "places")


def bits_of(k: Column) -> list[Column]:
    """The words of a set that holds the source at place ``k`` of its block only."""
    at = F.pmod(k, F.lit(BLOCK))
    one = F.expr("shiftleft(1L, CAST(pmod(k, 64) AS INT))")
    return [F.when(F.floor(at / WORD) == i, one).otherwise(F.lit(0).cast("long")).alias(w) for i, w in enumerate(BITS)]


def block_of(k: Column) -> Column:
    return F.floor(k / BLOCK).cast("long").alias("blk")


def merged(rows: DataFrame, *keys: str) -> DataFrame:
    return rows.groupBy(*keys).agg(*(F.bit_or(w).alias(w) for w in BITS))


def _some() -> Column:
    return reduce(lambda a, b: a | b, (F.col(w) != 0 for w in BITS))


def without(rows: DataFrame, other: DataFrame, on: list[str]) -> DataFrame:
    """The sets of ``rows`` less those of ``other``; rows whose set is left empty are dropped."""
    theirs = other.select(*on, *(F.col(w).alias(f"o{w}") for w in BITS))
    less = [F.col(w).bitwiseAND(F.bitwise_not(F.coalesce(f"o{w}", F.lit(0).cast("long")))).alias(w) for w in BITS]
    return rows.join(theirs, on, "left").select(*on, *less).where(_some())


def within(rows: DataFrame, other: DataFrame, on: list[str]) -> DataFrame:
    """The sets of ``rows`` cut with those of ``other`` (one row per ``on``)."""
    theirs = other.select(*on, *(F.col(w).alias(f"o{w}") for w in BITS))
    return rows.join(theirs, on).select(*rows.columns[: len(rows.columns) - WORDS], *(F.col(w).bitwiseAND(F.col(f"o{w}")).alias(w) for w in BITS)).where(_some())


def grown(arcs: DataFrame, front: DataFrame, before: DataFrame) -> DataFrame:
    """(blk, v, words) of the level after ``front``; in an undirected graph it can repeat the last two levels only."""
    reached = front.join(arcs.select(F.col("src").alias("v"), "dst"), "v").drop("v").withColumnRenamed("dst", "v")
    return without(merged(reached, "blk", "v"), merged(front.unionByName(before), "blk", "v"), ["blk", "v"])


def members(rows: DataFrame) -> DataFrame:
    """One row per bit that is set, as its source's place ``k``; the other columns stay."""
    rest = [c for c in rows.columns if c not in (*BITS, "blk")]
    words = rows.select(*rest, "blk", F.posexplode(F.array(*BITS)).alias("p", "w")).where("w <> 0")
    bits = words.select(*rest, "blk", "p", F.explode(F.expr("filter(sequence(0, 63), b -> (shiftrightunsigned(w, b) & 1L) = 1L)")).alias("b"))
    return bits.select(*rest, (F.col("blk") * BLOCK + F.col("p") * WORD + F.col("b")).alias("k"))


def distance_counts(g: Graph, blocks: int = 8) -> DataFrame:
    """(d, pairs): ordered pairs of all nodes, each node with itself included, by distance; ``blocks`` blocks of sources at a time.

    The work is n m / 64 words, the disk that of one batch of blocks."""
    with plainly_planned(g.nodes.sparkSession):
        counts = _counted(g, blocks)
    return g.nodes.sparkSession.createDataFrame(sorted(counts.items()), "d long, pairs long")


def _counted(g: Graph, blocks: int) -> dict[int, int]:
    places = placed(g.nodes.select("id"))
    start = places.select(block_of(F.col("k")), F.col("id").alias("v"), *bits_of(F.col("k")))
    held = sum((F.bit_count(w) for w in BITS), F.lit(0))
    counts: dict[int, int] = {}
    for first in range(0, -(-g.n // BLOCK), blocks):
        front = staged(start.where(F.col("blk").between(first, first + blocks - 1)), "shared-level")
        before = front.limit(0)
        for depth in range(MOST_ROUNDS):
            found = front.agg(F.sum(held.cast("long"))).first()[0]
            if not found:
                break
            counts[depth] = counts.get(depth, 0) + found
            after = staged(grown(g.arcs, front, before), "shared-level")
            discard(before)
            front, before = after, front
        else:
            raise RuntimeError(f"the search did not end in {MOST_ROUNDS} rounds")
        discard(before)
        discard(front)
    return counts


def bidirectional_distance(g: Graph, queries: DataFrame, seeds: DataFrame | None = None) -> DataFrame:
    """(qid, s, t, dist): two-sided search of all queries at once, whose levels the queries of one endpoint share.

    Sources go as sets of bits, targets as rows; a round extends the side with fewer rows by one
    level, and a pair whose depths add up to its distance has a node in both last levels. ``seeds`` (u, v, d, depth)
    start an endpoint from all nodes up to ``depth`` instead of itself; pairs whose seeds meet are not for this search."""
    with plainly_planned(g.nodes.sparkSession):
        dist = _two_sided(g, queries, seeds)
    return queries.join(dist, ["s", "t"], "left").select("qid", "s", "t", "dist")


def _two_sided(g: Graph, queries: DataFrame, seeds: DataFrame | None) -> DataFrame:
    """(s, t, dist) of the distinct pairs that are reached."""
    asked = staged(queries.select("s", "t").distinct(), "shared-queries")
    nodes = g.nodes.select("id")
    places = placed(asked.select(F.col("s").alias("id")).distinct().join(nodes, "id", "left_semi"))
    ends = staged(asked.select(F.col("t").alias("id")).distinct().join(nodes, "id", "left_semi"), "shared-targets")
    if seeds is None:
        seeds = places.select("id").union(ends.select("id")).distinct().select(F.col("id").alias("u"), F.col("id").alias("v"), F.lit(0).cast("long").alias("d"), F.lit(0).cast("long").alias("depth"))
    seeds = staged(seeds.select("u", "v", "d", "depth").where("d >= depth - 1 and d <= depth"), "shared-seeds")
    begun = seeds.join(places.withColumnRenamed("id", "u"), "u").select("d", "depth", block_of(F.col("k")), "v", *bits_of(F.col("k")))
    front, before = (staged(merged(begun.where(f"d = depth - {back}"), "blk", "v"), "shared-level") for back in (0, 1))
    aims = seeds.join(ends.withColumnRenamed("id", "u"), "u")
    near, last = (staged(aims.where(f"d = depth - {back}").select(F.col("u").alias("t"), "v"), "shared-near") for back in (0, 1))
    wanted = asked.join(ends.withColumnRenamed("id", "t"), "t", "left_semi").join(places.withColumnRenamed("id", "s"), "s")
    left = staged(merged(wanted.select("t", block_of(F.col("k")), *bits_of(F.col("k"))), "t", "blk"), "shared-left")
    hits, here, there = [], front.count(), near.count()
    for steps in range(MOST_ROUNDS):
        met = merged(near.join(front, "v").drop("v"), "t", "blk")
        hit = staged(within(met, left, ["t", "blk"]).withColumn("steps", F.lit(steps).cast("long")), "shared-hits")
        hits.append(hit)
        left_before, left = left, staged(without(left, hit, ["t", "blk"]), "shared-left")
        discard(left_before)
        if not (here and there) or left.isEmpty():
            break
        if here <= there:
            alive = F.broadcast(staged(merged(left, "blk"), "shared-alive"))
            after = staged(grown(g.arcs, within(front, alive, ["blk"]), before), "shared-level")
            discard(before)
            front, before, here = after, front, after.count()
        else:
            open_rows = near.join(left.select("t").distinct(), "t", "left_semi")
            reached = open_rows.join(g.arcs.select(F.col("src").alias("v"), "dst"), "v").select("t", F.col("dst").alias("v")).distinct()
            after = staged(reached.join(near.unionByName(last), ["t", "v"], "left_anti"), "shared-near")
            discard(last)
            near, last, there = after, near, after.count()
    else:
        raise RuntimeError(f"the search did not end in {MOST_ROUNDS} rounds")
    found = members(reduce(DataFrame.unionByName, hits)).join(F.broadcast(places), "k").select(F.col("id").alias("s"), "t", "steps")
    depths = seeds.select("u", "depth").distinct()
    found = found.join(depths.select(F.col("u").alias("s"), F.col("depth").alias("ds")), "s").join(depths.select(F.col("u").alias("t"), F.col("depth").alias("dt")), "t")
    return staged(found.select("s", "t", (F.col("steps") + F.col("ds") + F.col("dt")).alias("dist")), "shared-distances")


def search_work(g: Graph, queries: DataFrame) -> DataFrame:
    """(qid, s, t, dist, bfs_arcs, bidirectional_arcs): arcs that a search of the query alone reads, by the rules of ``baselines``.

    A search reads the arcs of whole levels, so both numbers follow from the degrees in each level around
    s and t. The levels of all endpoints are found at once, as sets of bits, and no query has rows of its own. An endpoint
    goes on while a query of it is open, so queries that are not reached have all levels of both ends."""
    with plainly_planned(g.nodes.sparkSession):
        work = staged(_worked(g, queries), "search-work")
    none = F.lit(0).cast("long")
    return queries.join(work, ["s", "t"], "left").select("qid", "s", "t", "dist", F.coalesce("bfs_arcs", none).alias("bfs_arcs"), F.coalesce("bidirectional_arcs", none).alias("bidirectional_arcs"))


def _worked(g: Graph, queries: DataFrame) -> DataFrame:
    """(s, t, dist, bfs_arcs, bidirectional_arcs) of the distinct pairs whose ends are both in the graph."""
    asked = queries.select("s", "t").distinct()
    ends = asked.select(F.explode(F.array("s", "t")).alias("id")).distinct()
    places = placed(ends.join(g.nodes.select("id"), "id", "left_semi"))
    of = {e: places.select(F.col("id").alias(e), F.col("k").alias(f"k{e}")) for e in ("s", "t")}
    pairs = staged(asked.join(of["s"], "s").join(of["t"], "t").withColumn("dist", F.lit(None).cast("long")), "work-pairs")
    front = staged(places.select(block_of(F.col("k")), F.col("id").alias("v"), *bits_of(F.col("k"))), "shared-level")
    levels, before = [], front.limit(0)
    for depth in range(MOST_ROUNDS):
        levels.append(front)
        word = F.get(F.array(*BITS), F.floor(F.pmod("ks", F.lit(BLOCK)) / WORD).cast("int")).alias("word")
        open_pairs = pairs.where("dist is null")
        there = front.join(open_pairs.select(F.col("t").alias("v"), block_of(F.col("ks")), "s", "ks"), ["v", "blk"]).select("s", F.col("v").alias("t"), "ks", word)
        hit = there.where(F.expr("(shiftrightunsigned(word, CAST(pmod(ks, 64) AS INT)) & 1L) = 1L")).select("s", "t", F.lit(depth).cast("long").alias("found"))
        pairs = staged(pairs.join(hit, ["s", "t"], "left").select("s", "t", "ks", "kt", F.coalesce("dist", "found").alias("dist")), "work-pairs")
        left = pairs.where("dist is null").select(F.explode(F.array("ks", "kt")).alias("k"))
        if left.isEmpty() or front.isEmpty():
            break
        alive = F.broadcast(merged(left.select(block_of(F.col("k")), *bits_of(F.col("k"))), "blk"))
        before, front = front, staged(grown(g.arcs, within(front, alive, ["blk"]), before), "shared-level")
    else:
        raise RuntimeError(f"the search did not end in {MOST_ROUNDS} rounds")
    rows = reduce(DataFrame.unionByName, (level.withColumn("d", F.lit(i)) for i, level in enumerate(levels)))
    load = members(rows.join(g.nodes.select(F.col("id").alias("v"), "deg"), "v").select("d", "deg", "blk", *BITS)).groupBy("k", "d").agg(F.sum("deg").alias("load"))
    loads = load.groupBy("k").agg(F.transform(F.sort_array(F.collect_list(F.struct("d", "load"))), lambda x: x["load"]).alias("loads"))
    both = pairs.join(loads.select(F.col("k").alias("ks"), F.col("loads").alias("ls")), "ks").join(loads.select(F.col("k").alias("kt"), F.col("loads").alias("lt")), "kt")
    none = F.lit(0).cast("long")
    read = F.when(F.col("dist").isNull(), F.col("ls")).otherwise(F.slice("ls", F.lit(1), F.col("dist").cast("int")))
    one = F.aggregate(read, none, lambda total, x: total + x)

    def step(x: Column, _: Column) -> Column:
        near, far = F.get("ls", x["i"]), F.get("lt", x["j"])
        goes_on = near.isNotNull() & far.isNotNull() & (F.col("dist").isNull() | (x["i"] + x["j"] < F.col("dist")))
        ahead = F.struct((x["i"] + 1).alias("i"), x["j"].alias("j"), (x["read"] + near).alias("read"))
        back = F.struct(x["i"].alias("i"), (x["j"] + 1).alias("j"), (x["read"] + far).alias("read"))
        return F.when(~goes_on, x).when(near <= far, ahead).otherwise(back)

    begun = F.struct(F.lit(0).alias("i"), F.lit(0).alias("j"), none.alias("read"))
    two = F.aggregate(F.concat("ls", "lt"), begun, step, lambda x: x["read"])
    return both.select("s", "t", "dist", one.alias("bfs_arcs"), two.alias("bidirectional_arcs"))
