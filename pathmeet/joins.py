"""Joins whose small side is broadcast only after its row count has been checked."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of slim columns that may be broadcast; beyond it a shuffled join is used.
BROADCAST_ROWS = 200_000


@contextmanager
def co_partitioned(spark: SparkSession) -> Iterator[None]:
    """Plans made and run inside may join on several keys by a partitioning on one of them.

    A table bucketed by a node is then read in place by a join on (node, member), where it
    would be shuffled again otherwise."""
    key = "spark.sql.requireAllClusterKeysForCoPartition"
    before = spark.conf.get(key)
    spark.conf.set(key, "false")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def fits(df: DataFrame, limit: int = BROADCAST_ROWS) -> bool:
    """True if ``df`` has at most ``limit`` rows; reads no more than ``limit + 1``."""
    return df.limit(limit + 1).count() <= limit


def bounded_join(left: DataFrame, right: DataFrame, on, how: str = "inner", limit: int = BROADCAST_ROWS) -> DataFrame:
    """Joins, broadcasting ``right`` behind a check of its size.

    ``right`` should be a written table, since the check reads it."""
    return left.join(F.broadcast(right) if fits(right, limit) else right, on, how)


def hot_join(left: DataFrame, right: DataFrame, on: list[str], size: str, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Left join of ``right``, one row per key, that sends no hot key through a shuffle.

    ``size`` is a column of ``right``: the rows of ``left`` (``rows`` in all) that have the key. Fewer than
    ``limit`` keys can hold more than ``rows / limit`` of them, so these are broadcast; the
    other keys are shuffled, and rows with a null in the key, which match nothing, are not."""
    if fits(right, limit):
        return left.join(F.broadcast(right), on, "left")
    hot = right.where(F.col(size) * limit > rows)
    blank = reduce(lambda a, b: a | b, (F.col(c).isNull() for c in on))
    whole = left.where(~blank)
    common = whole.join(F.broadcast(hot), on)
    rare = whole.join(F.broadcast(hot.select(*on)), on, "left_anti").join(right.where(F.col(size) * limit <= rows), on, "left")
    kinds = {f.name: f.dataType for f in right.schema.fields if f.name not in on}
    nothing = left.where(blank).select("*", *(F.lit(None).cast(t).alias(c) for c, t in kinds.items()))
    return common.unionByName(rare).unionByName(nothing)
