"""Anchor probabilities and draws (proportional to degree), and their ablations."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.functions.draws import fast_draw, md5_draw
from pathmeet.operators.graph import Graph
from pathmeet.scratch import staged


def steps(g: Graph):
    """Whole number of degree steps of a node: the ceiling of 2 n deg / m, in integers."""
    if 2 * g.n * g.n < 1 << 62:
        return F.expr(f"({2 * g.n}L * deg + {g.m - 1}L) div {max(1, g.m)}L")
    return F.ceil(F.lit(2 * g.n).cast("decimal(38,0)") * F.col("deg") / F.lit(g.m)).cast("long")


def inclusion_probability(g: Graph, alpha: float, calibration: str = "literal", weighting: str = "degree") -> DataFrame:
    """(id, deg, p). ``literal``: (m / (alpha n sqrt n)) times the degree steps, at most 1.

    ``anchor_count`` rescales so that the sum before clamping is m / (alpha sqrt n).
    ``weighting='uniform'`` gives every node the mean of the clamped probabilities."""
    base = g.m / (alpha * g.n * math.sqrt(g.n)) if g.n else 0.0
    raw = g.nodes.withColumn("steps", steps(g))
    if calibration == "anchor_count":
        total = raw.agg(F.sum("steps")).first()[0] or 1
        factor = F.lit(g.m / (alpha * math.sqrt(g.n))) / F.lit(float(total))
    elif calibration == "literal":
        factor = F.lit(base)
    else:
        raise ValueError(calibration)
    p = raw.select("id", "deg", F.least(F.lit(1.0), factor * F.col("steps")).alias("p"))
    if weighting == "uniform":
        mean = p.agg(F.avg(F.round("p", 12))).first()[0] or 0.0
        return p.withColumn("p", F.lit(round(mean, 9)))
    return p


def draw_anchors(
    g: Graph, alpha: float, seed: int = 7, calibration: str = "literal", draw: str = "md5", weighting: str = "degree", on_empty: str = "promote", explicit: DataFrame | None = None
) -> DataFrame:
    """Anchors (id, p, draw): the nodes whose draw is below their probability, or the ``explicit`` ones.

    Components without an anchor: ``promote`` adds their node of highest degree (least id),
    ``error`` raises, ``whole`` leaves them (their vicinities are whole components)."""
    if explicit is not None:
        chosen = explicit.select(F.col("id").cast("long"), F.lit(1.0).alias("p"), F.lit(0.0).alias("draw"))
        drawn = staged(chosen.join(g.nodes, "id", "left_semi"), "anchors")
    else:
        number = {"md5": md5_draw, "xxhash64": fast_draw}[draw](F.col("id"), seed)
        p = inclusion_probability(g, alpha, calibration, weighting)
        drawn = staged(p.withColumn("draw", number).where("draw < p").select("id", "p", "draw"), "anchors")
    if on_empty == "whole":
        return drawn
    if on_empty == "error":
        if not _unserved(g, drawn, g.components).isEmpty():
            raise ValueError("a component has no anchor")
        return drawn
    return promoted(g, drawn, g.components)


def _unserved(g: Graph, drawn: DataFrame, comps: DataFrame) -> DataFrame:
    """(comp, id): the node of highest degree (least id) of each component of ``comps`` without an anchor."""
    served = comps.join(drawn.select("id"), "id", "left_semi").select("comp").distinct()
    empty = comps.join(served, "comp", "left_anti").join(g.nodes, "id")
    return empty.groupBy("comp").agg(F.max_by("id", F.struct("deg", -F.col("id"))).alias("id"))


def promoted(g: Graph, drawn: DataFrame, comps: DataFrame) -> DataFrame:
    """The ``drawn`` anchors and one for each component of ``comps`` (id, comp) that has none."""
    best = _unserved(g, drawn, comps)
    return staged(drawn.unionByName(best.select("id", F.lit(1.0).alias("p"), F.lit(0.0).alias("draw"))), "anchors")


def calibrate_alpha(g: Graph, alpha: float, probe: DataFrame, tol: float = 0.2, seed: int = 7, rounds: int = 8) -> float:
    """The alpha for the literal formula at which the mean vicinity size over the ``probe`` nodes is alpha sqrt n.

    Bisection over a factor; stops within ``tol`` or when the vicinities no longer grow."""
    from pathmeet.operators.radius import radii
    from pathmeet.operators.vicinity import vicinities

    wanted, low, high = alpha * math.sqrt(g.n), 1.0, 64.0
    best = alpha
    for _ in range(rounds):
        middle = math.sqrt(low * high)
        found = radii(g, draw_anchors(g, alpha * middle, seed))
        size = vicinities(g, found, sources=probe).groupBy("u").count().agg(F.avg("count")).first()[0] or 0.0
        best = alpha * middle
        if abs(size - wanted) <= tol * wanted:
            break
        low, high = (middle, high) if size < wanted else (low, middle)
    return best
