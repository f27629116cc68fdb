"""Synthetic graphs from ``spark.range``: closed-form families and a power-law family."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def ring(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst"))


def path(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))


def star(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(1, n).select(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst"))


def complete(spark: SparkSession, n: int) -> DataFrame:
    ids = spark.range(n)
    return ids.select(F.col("id").alias("src"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))).alias("dst")).where("src < dst")


def grid(spark: SparkSession, rows: int, cols: int) -> DataFrame:
    cell = spark.range(rows * cols)
    right = cell.where(F.col("id") % cols < cols - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    return right.union(cell.where(F.col("id") < (rows - 1) * cols).select("id", F.col("id") + cols))


def lollipop(spark: SparkSession, clique: int, tail: int) -> DataFrame:
    return complete(spark, clique).union(spark.range(clique - 1, clique + tail - 1).select("id", F.col("id") + 1))


def power_law(spark: SparkSession, n: int, mean_degree: float = 10.0, exponent: float = 2.3, seed: int = 7) -> DataFrame:
    """Edges with endpoints drawn by rank from a power law (inverse transform of hashed draws)."""
    shape = 1.0 - 1.0 / (exponent - 1.0)

    def endpoint(salt: int):
        u = (F.shiftrightunsigned(F.xxhash64("id", F.lit(salt)), 11).cast("double")) / float(1 << 53)
        return F.least(F.lit(n - 1), F.floor(F.pow(u, F.lit(1.0 / shape)) * n)).cast("long")

    return spark.range(int(n * mean_degree / 2)).select(endpoint(seed).alias("src"), endpoint(seed + 1).alias("dst")).where("src <> dst")
