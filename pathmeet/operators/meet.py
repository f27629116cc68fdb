"""Batch distance queries against an index.

Shortcuts first, in a fixed order: equal endpoints, s or t an anchor, t in the vicinity
of s, s in that of t. They are needed for correctness, not only for speed, as soon as less
than the whole vicinity is probed. What is left explodes to the probed members of one
endpoint, each of which is looked up in the vicinity of the other."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathmeet.joins import bounded_join, co_partitioned
from pathmeet.operators.index import Index
from pathmeet.scratch import staged


def annotate(index: Index, queries: DataFrame) -> DataFrame:
    """Adds radii and components of both endpoints; null where a node is unknown."""
    of = index.radius.join(index.graph.components.withColumnRenamed("id", "u"), "u", "left")
    one, two = (of.select(F.col("u").alias(k), F.col("r").alias(f"r_{k}"), F.col("anchor").alias(f"a_{k}"), F.coalesce("comp", "u").alias(f"c_{k}")) for k in ("s", "t"))
    return queries.join(one, "s", "left").join(two, "t", "left")


def shortcuts(index: Index, known: DataFrame) -> DataFrame:
    """(qid, dist, case, witness) of the queries that one lookup answers."""
    same = known.where("s = t and c_s is not null").select("qid", F.lit(0).cast(_kind(index)).alias("dist"), F.lit("same").alias("case"), F.col("s").alias("witness"), F.lit(0).alias("rank"))
    apart = known.where("s <> t and c_s = c_t")
    anchors = index.anchors.select(F.col("id"))
    at_s = apart.join(anchors.select(F.col("id").alias("s")), "s", "left_semi")
    at_t = apart.join(anchors.select(F.col("id").alias("t")), "t", "left_semi")
    tables = index.anchor_dist(at_s.select(F.col("s").alias("id")).union(at_t.select(F.col("t").alias("id"))).distinct())
    found = [
        same,
        at_s.join(tables.select(F.col("a").alias("s"), F.col("v").alias("t"), "d"), ["s", "t"]).select("qid", F.col("d").alias("dist"), F.lit("source_anchor").alias("case"), F.col("s").alias("witness"), F.lit(1).alias("rank")),
        at_t.join(tables.select(F.col("a").alias("t"), F.col("v").alias("s"), "d"), ["s", "t"]).select("qid", F.col("d").alias("dist"), F.lit("target_anchor").alias("case"), F.col("t").alias("witness"), F.lit(2).alias("rank")),
    ]
    member = of_nodes(index.vicinity, apart.select(F.col("s").alias("u")).union(apart.select(F.col("t").alias("u"))))
    if index.graph.weighted:  # labels on the rim are upper bounds there, so only ball members count
        member = member.where("inside")
    found.append(apart.join(member.select(F.col("u").alias("s"), F.col("v").alias("t"), "d"), ["s", "t"]).select("qid", F.col("d").alias("dist"), F.lit("target_in_source").alias("case"), F.col("t").alias("witness"), F.lit(3).alias("rank")))
    found.append(apart.join(member.select(F.col("u").alias("t"), F.col("v").alias("s"), "d"), ["s", "t"]).select("qid", F.col("d").alias("dist"), F.lit("source_in_target").alias("case"), F.col("s").alias("witness"), F.lit(4).alias("rank")))
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    first = out.groupBy("qid").agg(F.min(F.struct("rank", "dist", "case", "witness")).alias("x"))
    return first.select("qid", "x.dist", "x.case", "x.witness")


def _kind(index: Index):
    return index.vicinity.schema["d"].dataType


def probed_rows(index: Index, probe: str) -> DataFrame:
    """(u, v, d) that are iterated: the boundary, the rim or the whole vicinity."""
    if probe == "boundary":
        return index.boundary.select("u", "v", "d")
    return index.rim() if probe == "rim" else index.vicinity.select("u", "v", "d")


def choose_side(queries: DataFrame, probes: DataFrame, side: str) -> DataFrame:
    """(qid, own, other): the endpoint whose rows are iterated, and the one that is looked up."""
    if side == "source":
        return queries.select("qid", F.col("s").alias("own"), F.col("t").alias("other"))
    if side == "target":
        return queries.select("qid", F.col("t").alias("own"), F.col("s").alias("other"))
    sizes = probes.groupBy("u").agg(F.count("*").alias("n"))
    both = queries.join(sizes.select(F.col("u").alias("s"), F.col("n").alias("ns")), "s", "left").join(sizes.select(F.col("u").alias("t"), F.col("n").alias("nt")), "t", "left")
    source = F.coalesce("ns", F.lit(0)) <= F.coalesce("nt", F.lit(0))
    return both.select("qid", F.when(source, F.col("s")).otherwise(F.col("t")).alias("own"), F.when(source, F.col("t")).otherwise(F.col("s")).alias("other"))


def of_nodes(rows: DataFrame, nodes: DataFrame) -> DataFrame:
    """The rows of ``nodes`` (u), which are counted first: those of a batch are few beside an index."""
    return bounded_join(rows, staged(nodes.distinct(), "endpoints"), "u", "left_semi")


def meet(index: Index, rest: DataFrame, probe: str, side: str) -> DataFrame:
    """(qid, dist, witness, probes): least sum over members of both vicinities; null dist if they do not meet."""
    rows = probed_rows(index, probe)
    sided = choose_side(rest, rows, side)
    probes = sided.join(rows.select(F.col("u").alias("own"), F.col("v").alias("x"), F.col("d").alias("d1")), "own")
    looked = probes.join(of_nodes(index.vicinity, sided.select(F.col("other").alias("u"))).select(F.col("u").alias("other"), F.col("v").alias("x"), F.col("d").alias("d2")), ["other", "x"], "left")
    total = F.col("d1") + F.col("d2")
    return looked.groupBy("qid").agg(F.min(F.when(total.isNotNull(), F.struct(total.alias("dist"), F.col("x").alias("witness")))).alias("best"), F.count("*").alias("probes")).select("qid", "best.dist", "best.witness", "probes")


def meetings(index: Index, queries: DataFrame) -> DataFrame:
    """(qid, s, t, dist, probes) of the queries that ``distance`` answers with the case meet, in unweighted graphs.

    Nodes that meet lie in one component, and a pair with an anchor end has an answer in its table; so
    neither components are labelled nor tables built where only meetings are asked for."""
    if index.graph.weighted:
        raise ValueError("a weighted meeting is certified by distance()")
    rest = staged(queries.select("qid", "s", "t").where("s <> t"), "queries")
    member = of_nodes(index.vicinity, rest.select(F.col("s").alias("u")).union(rest.select(F.col("t").alias("u"))))
    for one, two in (("s", "t"), ("t", "s")):
        rest = bounded_join(rest, index.anchors.select(F.col("id").alias(one)), one, "left_anti")
        rest = rest.join(member.select(F.col("u").alias(one), F.col("v").alias(two)), [one, two], "left_anti")
    rest = staged(rest.select("qid", "s", "t"), "open-queries")
    with co_partitioned(rest.sparkSession):
        met = staged(meet(index, rest, "boundary", "source"), "met")
    return rest.join(met.where("dist is not null").select("qid", "dist", "probes"), "qid")


def distance(index: Index, queries: DataFrame, probe: str | None = None, side: str = "source", fallback: str = "none") -> DataFrame:
    """One row per query (qid, s, t): dist, case, witness, probes, lower, upper, certified.

    ``probe``: boundary (default, unweighted), rim (default, weighted) or full. A weighted meeting
    is certified exact if it is at most r(s) + r(t); others keep it as ``upper``. Boundary probing
    of weighted graphs needs exact rim labels. ``fallback``: none, exact, continue or bounds."""
    from pathmeet.operators import fallback as after

    weighted = index.graph.weighted
    probe = probe or ("rim" if weighted else "boundary")
    known = staged(annotate(index, queries.select("qid", "s", "t")), "queries")
    spark = known.sparkSession
    with co_partitioned(spark):
        short = staged(shortcuts(index, known), "shortcuts")
    rest = known.where("s <> t and c_s = c_t").join(short.select("qid"), "qid", "left_anti")
    with co_partitioned(spark):
        met = staged(meet(index, rest, probe, side), "met")
    reach = F.col("r_s") + F.col("r_t")
    joined = known.join(short.select("qid", F.col("dist").alias("d0"), F.col("case").alias("c0"), F.col("witness").alias("w0")), "qid", "left").join(met, "qid", "left")
    exact = F.col("c0").isNotNull() | (F.col("dist").isNotNull() & (F.lit(not weighted) | (F.col("dist") <= reach)))
    case = (
        F.when(F.col("c_s").isNull() | F.col("c_t").isNull(), "unknown_node")
        .when(F.col("c0").isNotNull(), F.col("c0"))
        .when(F.col("c_s") != F.col("c_t"), "unreachable")
        .when(exact, "meet")
        .otherwise("unanswered")
    )
    answer = F.when(F.col("c0").isNotNull(), F.col("d0")).when(exact, F.col("dist"))
    open_lower = reach + (0 if weighted else 1)
    out = joined.select(
        "qid", "s", "t", answer.alias("dist"), case.alias("case"), F.coalesce("w0", F.when(exact, F.col("witness"))).alias("witness"), F.coalesce("probes", F.lit(0).cast("long")).alias("probes"),
        F.coalesce(answer, F.when(case == "unanswered", open_lower)).alias("lower"), F.coalesce(answer, F.when(case == "unanswered", F.col("dist"))).alias("upper"), exact.alias("certified"),
    )
    if fallback == "none":
        return out
    out = staged(out, "answers")
    return {"exact": after.exact, "continue": after.continued, "bounds": after.bounds}[fallback](index, out)


def pairs_distance(index: Index, sample: DataFrame, probe: str | None = None) -> DataFrame:
    """(s, t, dist) for all pairs s < t of the sample nodes (id) whose probed rows meet.

    A sparse minimum-plus product on the shared member, combined before the shuffle; hot
    members are left to the skew handling of the join."""
    probe = probe or "boundary"
    chosen = staged(sample.select(F.col("id").alias("u")), "pair-sample")
    rows = bounded_join(probed_rows(index, probe), chosen, "u", "left_semi")
    vic = bounded_join(index.vicinity, chosen, "u", "left_semi")
    one = rows.select(F.col("u").alias("s"), "v", F.col("d").alias("d1"))
    two = vic.select(F.col("u").alias("t"), "v", F.col("d").alias("d2"))
    return one.join(two, "v").where("s < t").groupBy("s", "t").agg(F.min(F.col("d1") + F.col("d2")).alias("dist"))
