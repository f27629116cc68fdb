"""Cost and accuracy measures over graphs, indexes and answers."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathmeet.functions.kernels import MOST_ARCS
from pathmeet.operators.anchors import inclusion_probability
from pathmeet.operators.graph import Graph
from pathmeet.operators.index import Index, anchored
from pathmeet.operators.vicinity import boundaries, inner_arcs, vicinities
from pathmeet.scratch import drop_path, made

#: Rows of vicinities that may lie on disk at once where only their number is asked for.
BLOCK_ROWS = 100_000_000
#: Places by which nodes are dealt to blocks.
PLACES = 1 << 20


def coverage(answers: DataFrame) -> DataFrame:
    """(case, pairs, share): pairs by the way they were answered, and a total of the answered ones (case null).

    Shares are of all pairs; grouping sets compute both levels in one pass."""
    answered = F.col("dist").isNotNull()
    by = answers.rollup("case").agg(F.count("*").alias("rows"), F.count_if(answered).alias("answered"), F.grouping("case").alias("all_cases"))
    total = F.sum(F.when(F.col("all_cases") == 1, F.col("rows"))).over(Window.partitionBy())
    count = F.when(F.col("all_cases") == 1, F.col("answered")).otherwise(F.col("rows"))
    return by.select("case", count.alias("pairs"), F.round(count / total, 6).alias("share"))


def accuracy(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: pairs, answered, wrong, loss (share not answered). ``truth``: (s, v, d)."""
    joined = answers.join(truth.select("s", F.col("v").alias("t"), F.col("d").alias("true_dist")), ["s", "t"], "left")
    wrong = F.count_if(F.col("dist").isNotNull() & ~F.col("dist").eqNullSafe(F.col("true_dist")))
    return joined.agg(F.count("*").alias("pairs"), F.count("dist").alias("answered"), wrong.alias("wrong"), F.round(1 - F.count("dist") / F.count("*"), 6).alias("loss"))


def vicinity_size_profile(g: Graph, vic: DataFrame, alpha: float) -> DataFrame:
    """One row: mean and largest vicinity, against alpha sqrt n and as a share of n."""
    sizes = vic.groupBy("u").agg(F.count("*").alias("size"))
    return sizes.agg(
        F.count("*").alias("nodes"), F.round(F.avg("size"), 6).alias("mean_size"), F.max("size").alias("max_size"), F.round(F.avg("size") / (alpha * math.sqrt(g.n)), 6).alias("of_expected"),
        F.round(F.max("size") / g.n, 6).alias("max_share"),
    )


def anchor_profile(g: Graph, anchors: DataFrame, alpha: float, calibration: str = "literal") -> DataFrame:
    """One row: expected and drawn number of anchors, against m / (alpha sqrt n)."""
    expected = inclusion_probability(g, alpha, calibration).agg(F.round(F.sum("p"), 6).alias("expected"))
    return expected.crossJoin(anchors.agg(F.count("*").alias("drawn"))).withColumn("stated", F.round(F.lit(g.m / (alpha * math.sqrt(g.n))), 6))


def boundary_cdf(g: Graph, bnd: DataFrame, sample: DataFrame) -> DataFrame:
    """(u, size, share, cdf) over the sample nodes: boundary size, as a share of n, and its rank."""
    sizes = sample.select(F.col("id").alias("u")).join(bnd.groupBy("u").agg(F.count("*").alias("size")), "u", "left").select("u", F.coalesce("size", F.lit(0)).alias("size"))
    return sizes.select("u", "size", F.round(F.col("size") / g.n, 9).alias("share"), F.round(F.cume_dist().over(Window.orderBy("size")), 9).alias("cdf"))


def radius_profile(radii: DataFrame) -> DataFrame:
    """(r, nodes) with the mean over all nodes in every row."""
    by = radii.groupBy("r").agg(F.count("*").alias("nodes"))
    everything = Window.partitionBy()
    return by.select("r", "nodes", F.round(F.sum(F.col("r") * F.col("nodes")).over(everything) / F.sum("nodes").over(everything), 6).alias("mean_radius"))


def probe_profile(answers: DataFrame) -> DataFrame:
    """One row over met and unanswered pairs: probes on average and at worst, and lookups with the four shortcut tests."""
    tried = answers.where(F.col("case").isin("meet", "unanswered"))
    return tried.agg(F.count("*").alias("pairs"), F.round(F.avg("probes"), 6).alias("mean_probes"), F.max("probes").alias("worst_probes"), F.round(F.avg(F.col("probes") + 4), 6).alias("mean_lookups"))


def memory_profile(index: Index, full_tables: bool = True) -> DataFrame:
    """(part, entries, per_node, of_all_pairs): entries of each part against n squared, and those of storing all pairs."""
    return _profile(index.graph, index.vicinity.count(), index.boundary.count(), index.anchors.count())


def memory_profile_by_blocks(g: Graph, alpha: float, block_rows: int = BLOCK_ROWS, most_arcs: int = MOST_ARCS) -> DataFrame:
    """``memory_profile`` of the index of every node, whose parts are never on disk at once.

    Vicinities and boundaries are built for one block of nodes after the other, counted and deleted. The first
    block has as many nodes as alpha root n rows each allow; later ones follow the rows that were found. The kernel searches graphs
    of up to ``most_arcs`` arcs, the joins larger ones."""
    anchors, radius = anchored(g, alpha)
    kernel = not g.weighted and 2 * g.m <= most_arcs
    inner = None if g.weighted or kernel else inner_arcs(g, radius)
    place = F.pmod(F.xxhash64("id"), F.lit(PLACES))
    done, step = 0, max(1, min(PLACES, int(PLACES * block_rows / max(1.0, alpha * g.n * math.sqrt(g.n)))))
    vic_rows = bnd_rows = 0
    while done < PLACES:
        before = made()
        sources = g.nodes.where((place >= done) & (place < done + step)).select("id")
        vic = vicinities(g, radius, sources, engine="kernel" if kernel else "relational", inner=inner)
        bnd = boundaries(g, vic, radius)
        vic_rows, bnd_rows = vic_rows + vic.count(), bnd_rows + bnd.count()
        for path in made() - before:
            drop_path(vic.sparkSession, path)
        done += step
        step = max(1, min(PLACES - done, int(done * block_rows / max(1, vic_rows))))
    return _profile(g, vic_rows, bnd_rows, anchors.count())


def _profile(g: Graph, vic_rows: int, bnd_rows: int, anchors: int) -> DataFrame:
    n = g.n
    entries = {
        "vicinities": vic_rows, "boundaries": bnd_rows, "anchor_tables": anchors * n,
        "all_pairs_squared": n * n, "all_pairs_halved": n * (n - 1) // 2, "four_root_n": int(4 * n * math.sqrt(n)),
    }
    rows = g.arcs.sparkSession.createDataFrame(list(entries.items()), "part string, entries long")
    return rows.select("part", "entries", F.round(F.col("entries") / n, 6).alias("per_node"), F.round(F.col("entries") / float(n * n), 9).alias("of_all_pairs"))


def build_cost(g: Graph, vic: DataFrame, alpha: float) -> DataFrame:
    """One row: arcs that the search of a vicinity reads, on average and at most, against alpha sqrt n, and its most rounds."""
    read = vic.where("inside").join(g.nodes.select(F.col("id").alias("v"), "deg"), "v").groupBy("u").agg(F.sum("deg").alias("arcs"), (F.max("d") + 1).alias("rounds"))
    return read.agg(
        F.count("*").alias("nodes"), F.round(F.avg("arcs"), 6).alias("mean_arcs"), F.max("arcs").alias("most_arcs"),
        F.round(F.avg("arcs") / (alpha * math.sqrt(g.n)), 6).alias("of_expected"), F.max("rounds").alias("rounds"),
    )


def explored_fraction(g: Graph, answers: DataFrame) -> DataFrame:
    """One row: the share of the nodes that a query probes, on average and at worst."""
    tried = answers.where(F.col("case").isin("meet", "unanswered"))
    return tried.agg(F.round(F.avg("probes") / g.n, 9).alias("mean_share"), F.round(F.max("probes") / g.n, 9).alias("worst_share"))


def stretch_profile(estimates: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: estimate over true distance, on average and at worst, and the share of exact ones. ``truth``: (s, v, d)."""
    joined = estimates.join(truth.select("s", F.col("v").alias("t"), F.col("d").alias("true_dist")), ["s", "t"]).where("true_dist > 0")
    ratio = F.col("dist") / F.col("true_dist")
    return joined.agg(F.count("*").alias("pairs"), F.round(F.avg(ratio), 6).alias("mean_stretch"), F.round(F.max(ratio), 6).alias("worst_stretch"), F.round(F.avg((F.col("dist") == F.col("true_dist")).cast("double")), 6).alias("exact_share"))


def coverage_by_bound(radii: DataFrame, pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: pairs of which neither end is an anchor and those with d <= r(s) + r(t), without building a vicinity."""
    one = radii.select(F.col("u").alias("s"), F.col("r").alias("rs"))
    two = radii.select(F.col("u").alias("t"), F.col("r").alias("rt"))
    known = pairs.join(one, "s").join(two, "t").where("rs > 0 and rt > 0").join(truth.select("s", F.col("v").alias("t"), "d"), ["s", "t"])
    return known.agg(F.count("*").alias("pairs"), F.count_if(F.col("d") <= F.col("rs") + F.col("rt")).alias("meeting"))
