"""Level-by-level expansion: the loop under every unweighted search of this package.

A round joins the last level with the arcs in place, keeps one row per (source, node) by
minima (combined before the shuffle), and drops what the last two levels hold: in an
undirected graph the neighbours of level k lie in levels k-1, k and k+1. Every level is a
written table, so lineage stays short and a lost executor repeats one round at most."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathmeet.scratch import staged

#: Rounds after which a search is in error, and appended rounds of labels that are merged into one table.
MOST_ROUNDS, MERGED = 10_000, 8


def levels(
    arcs: DataFrame,
    start: DataFrame,
    keys: tuple[str, ...] = ("u",),
    carry: dict[str, Column] | None = None,
    may_expand: Column | None = None,
    stop: int | None = None,
    directed: bool = False,
    after: Callable[[DataFrame, int], DataFrame] | None = None,
) -> DataFrame:
    """All (keys, v, d, carried) reached from ``start`` (keys, v, carried).

    ``carry`` gives, for each carried column, its value in the next level as an aggregate over
    the row that reaches a node (columns of the level, and ``dst``). ``may_expand`` filters the
    rows that are expanded. ``directed`` drops against all levels. ``after`` may filter a new level."""
    carry = carry or {}
    on = [*keys, "v"]
    last = staged(start.withColumn("d", F.lit(0).cast("long")).select(*on, "d", *carry), "level")
    held, depth = [last], 0
    while stop is None or depth < stop:
        depth += 1
        if depth > MOST_ROUNDS:
            raise RuntimeError(f"the search did not end in {MOST_ROUNDS} rounds")
        grown = (last if may_expand is None else last.where(may_expand)).join(arcs.select(F.col("src").alias("v"), "dst"), "v")
        reached = grown.groupBy(*keys, "dst").agg(*(value.alias(name) for name, value in carry.items()), F.lit(depth).cast("long").alias("d"))
        reached = reached.withColumnRenamed("dst", "v")
        seen = reduce(DataFrame.unionByName, (old.select(*on) for old in (held if directed else held[-2:])))
        reached = reached.join(seen, on, "left_anti")
        new = reached.select(*on, "d", *carry)
        last = staged(new if after is None else after(new, depth), "level")
        if last.isEmpty():
            break
        held.append(last)
    out = held[0]
    for level in held[1:]:
        out = out.unionByName(level)
    return out


def relaxed(arcs: DataFrame, start: DataFrame, keys: tuple[str, ...], tie: str, may_expand: Column | None = None, opened: DataFrame | None = None, after: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Label-correcting search for weighted arcs: (keys, v, d, tie, carried ``r``) at the fixpoint.

    ``start`` has (keys, v, d, tie, r). Only labels that got smaller are expanded in the next
    round; a label is the least (d, tie) seen. A round joins its candidates with the labels of the
    same nodes and appends those that are smaller, so earlier labels are not written again; the
    appended rounds are merged when there are ``MERGED`` of them. ``opened`` (v) restricts the first round, where the
    other labels are known to be settled. ``after`` may filter the labels that a round expands."""
    on = [*keys, "v"]
    rows = [*on, "d", tie, "r"]
    start = staged(start.select(*rows), "labels")
    rounds, moved = [start], start if opened is None else start.join(opened, "v", "left_semi")

    def least(labels: list[DataFrame]) -> DataFrame:
        """The label of each node: a later one is always better than an earlier one."""
        union = reduce(DataFrame.unionByName, (x.withColumn("round", F.lit(i)) for i, x in enumerate(labels)))
        return union.groupBy(*on).agg(F.max(F.struct("round", "d", tie, "r")).alias("x")).select(*on, "x.d", f"x.{tie}", "x.r")

    for _ in range(MOST_ROUNDS):
        open_rows = moved if may_expand is None else moved.where(may_expand)
        open_rows = open_rows if after is None else after(open_rows)
        reached = open_rows.join(arcs.select(F.col("src").alias("v"), "dst", "w"), "v")
        reached = reached.select(*keys, F.col("dst").alias("v"), (F.col("d") + F.col("w")).alias("d"), (F.col("v") if tie == "parent" else F.col(tie)).alias(tie), "r")
        best = reached.groupBy(*on).agg(F.min(F.struct("d", tie)).alias("x"), F.first("r").alias("r2"))
        held = least(rounds).select(*on, F.col("d").alias("d0"), F.col(tie).alias("t0"), F.col("r").alias("r0"))
        smaller = F.col("d0").isNull() | (F.col("x.d") < F.col("d0"))
        if tie != "parent":  # a parent of equal distance could close a ring of zero weights
            smaller = smaller | ((F.col("x.d") == F.col("d0")) & (F.col(f"x.{tie}") < F.col("t0")))
        better = best.join(held, on, "left").where(smaller).select(*on, "x.d", f"x.{tie}", F.coalesce("r0", "r2").alias("r"))
        moved = staged(better.select(*rows), "labels")
        if moved.isEmpty():
            return least(rounds).select(*rows)
        rounds.append(moved)
        if len(rounds) >= MERGED:
            rounds = [staged(least(rounds).select(*rows), "labels")]
    raise RuntimeError(f"the search did not end in {MOST_ROUNDS} rounds")
