"""Two vicinity definitions that fail: a fixed number of nodes, and a fixed radius."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathmeet.operators.frontier import levels
from pathmeet.operators.graph import Graph
from pathmeet.scratch import staged


def fixed_size_vicinities(g: Graph, k: int, sources: DataFrame | None = None) -> DataFrame:
    """(u, v, d): the ``k`` nodes nearest to u, ties by id; u itself is a self row besides.

    Nodes at equal distance may be cut apart, so meetings can give too large distances."""
    ids = (g.nodes if sources is None else sources).select(F.col("id").alias("u"), F.col("id").alias("v"))
    found: DataFrame | None = None
    last, before, depth = staged(ids.withColumn("d", F.lit(0).cast("long")), "nearest"), None, 0
    found, full = last, None
    while True:
        depth += 1
        grown = last.join(g.arcs.select(F.col("src").alias("v"), "dst"), "v").select("u", F.col("dst").alias("v")).distinct()
        for old in (last, before):
            if old is not None:
                grown = grown.join(old.select("u", "v"), ["u", "v"], "left_anti")
        new = staged(grown.withColumn("d", F.lit(depth).cast("long")), "nearest")
        if new.isEmpty():
            break
        found = staged(found.unionByName(new), "nearest-all")
        open_ids = found.groupBy("u").agg(F.count("*").alias("held")).where(F.col("held") <= k).select("u")
        before, last = last, staged(new.join(open_ids, "u", "left_semi"), "nearest-open")
    place = F.row_number().over(Window.partitionBy("u").orderBy("d", "v"))
    return found.withColumn("place", place).where(F.col("place") <= k + 1).select("u", "v", "d")


def fixed_radius_vicinities(g: Graph, rho: int, sources: DataFrame | None = None) -> DataFrame:
    """(u, v, d): everything within ``rho`` hops; exact where it meets, without a bound on size."""
    ids = (g.nodes if sources is None else sources).select(F.col("id").alias("u"), F.col("id").alias("v"))
    return levels(g.arcs, ids, stop=rho)


def meet_members(vic: DataFrame, pairs: DataFrame) -> DataFrame:
    """(s, t, dist): least sum over common members, whatever the vicinities are."""
    one = vic.select(F.col("u").alias("s"), F.col("v").alias("x"), F.col("d").alias("d1"))
    two = vic.select(F.col("u").alias("t"), F.col("v").alias("x"), F.col("d").alias("d2"))
    return pairs.select("s", "t").join(one, "s").join(two, ["t", "x"]).groupBy("s", "t").agg(F.min(F.col("d1") + F.col("d2")).alias("dist"))
