"""What becomes of queries whose vicinities do not meet: exact searches, or bounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.operators.baselines import weighted_sssp
from pathmeet.operators.index import Index
from pathmeet.operators.shared import bidirectional_distance
from pathmeet.scratch import staged


def _merged(answers: DataFrame, found: DataFrame, case: str) -> DataFrame:
    extra = found.select("qid", F.col("dist").alias("found"))
    both = answers.join(extra, "qid", "left")
    hit = F.col("found").isNotNull()
    return both.select(
        "qid", "s", "t", F.coalesce("dist", "found").alias("dist"), F.when(hit, case).otherwise(F.col("case")).alias("case"), "witness", "probes",
        F.coalesce("found", "lower").alias("lower"), F.coalesce("found", "upper").alias("upper"), (F.col("certified") | hit).alias("certified"),
    )


def exact(index: Index, answers: DataFrame) -> DataFrame:
    """Runs the bidirectional (weighted: single-source) search for the unanswered queries only."""
    open_rows = answers.where("case = 'unanswered'").select("qid", "s", "t")
    if index.graph.weighted:
        reached = weighted_sssp(index.graph, open_rows.select(F.col("s").alias("id")).distinct())
        found = open_rows.join(reached.select("s", F.col("v").alias("t"), F.col("d").alias("dist")), ["s", "t"])
    else:
        found = bidirectional_distance(index.graph, open_rows)
    return _merged(answers, found, "fallback_exact")


def continued(index: Index, answers: DataFrame) -> DataFrame:
    """Goes on from the stored vicinities: all nodes up to the radius are known on both sides."""
    if index.graph.weighted:
        raise ValueError("continuation is for unweighted graphs")
    open_rows = answers.where("case = 'unanswered'").select("qid", "s", "t")
    ends = open_rows.select(F.col("s").alias("u")).union(open_rows.select(F.col("t").alias("u"))).distinct()
    seeds = index.vicinity.select("u", "v", "d").join(ends, "u", "left_semi").join(index.radius.select("u", F.col("r").alias("depth")), "u").select("u", "v", "d", "depth")
    return _merged(answers, bidirectional_distance(index.graph, open_rows, seeds), "fallback_continue")


def _anchor_distances(index: Index, both: DataFrame) -> DataFrame:
    """(a, v, d) from the nearest anchor of each end to the other end: of these pairs only, where tables are not built yet."""
    if index.tables is not None or index.graph.weighted:
        return index.anchor_dist(both.select(F.col("as").alias("id")).union(both.select(F.col("at").alias("id"))).distinct())
    pairs = both.select(F.col("as").alias("s"), "t").union(both.select(F.col("at").alias("s"), F.col("s").alias("t"))).distinct()
    found = bidirectional_distance(index.graph, pairs.withColumn("qid", F.lit(0)))
    return found.where("dist is not null").select(F.col("s").alias("a"), F.col("t").alias("v"), F.col("dist").alias("d"))


def bounds(index: Index, answers: DataFrame) -> DataFrame:
    """Triangle bounds through the nearest anchors; exact where lower and upper coincide."""
    open_rows = answers.where("case = 'unanswered'").select("qid", "s", "t", F.col("lower").alias("low0"), F.col("upper").alias("up0"))
    near = index.radius.select("u", "r", "anchor")
    both = open_rows.join(near.select(F.col("u").alias("s"), F.col("r").alias("rs"), F.col("anchor").alias("as")), "s").join(near.select(F.col("u").alias("t"), F.col("r").alias("rt"), F.col("anchor").alias("at")), "t")
    both = staged(both, "bounds-open")
    tables = _anchor_distances(index, both)
    both = both.join(tables.select(F.col("a").alias("as"), F.col("v").alias("t"), F.col("d").alias("as_t")), ["as", "t"]).join(tables.select(F.col("a").alias("at"), F.col("v").alias("s"), F.col("d").alias("at_s")), ["at", "s"])
    upper = F.least(F.col("rs") + F.col("as_t"), F.col("rt") + F.col("at_s"), "up0")
    lower = F.greatest("low0", F.abs(F.col("as_t") - F.col("rs")), F.abs(F.col("at_s") - F.col("rt")))
    new = both.select("qid", lower.alias("low"), upper.alias("up"))
    joined = answers.join(new, "qid", "left")
    tight = F.col("low") == F.col("up")
    return joined.select(
        "qid", "s", "t", F.coalesce("dist", F.when(tight, F.col("up"))).alias("dist"), F.when(tight, "bounds_exact").when(F.col("low").isNotNull(), "bounds").otherwise(F.col("case")).alias("case"), "witness", "probes",
        F.coalesce("low", "lower").alias("lower"), F.coalesce("up", "upper").alias("upper"), (F.col("certified") | F.coalesce(tight, F.lit(False))).alias("certified"),
    )
