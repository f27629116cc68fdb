"""The offline index: radii, vicinities, boundaries and anchor tables, in memory of the session or on disk."""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathmeet.components import component_labels
from pathmeet.operators.anchors import draw_anchors, promoted
from pathmeet.operators.graph import Graph
from pathmeet.operators.radius import radii
from pathmeet.operators.vicinity import anchor_tables, boundaries, inner_arcs, rims, vicinities
from pathmeet.scratch import bucketed, delete_folder, read_file, replace_file


@dataclass
class Index:
    graph: Graph
    anchors: DataFrame
    radius: DataFrame
    vicinity: DataFrame
    boundary: DataFrame
    #: Distances from the anchors of the batch, or of all; built when first asked for.
    tables: DataFrame | None = None

    def anchor_dist(self, endpoints: DataFrame | None = None) -> DataFrame:
        """Anchor tables: those built before, or of the anchors among ``endpoints`` (id)."""
        if self.tables is not None:
            return self.tables
        return anchor_tables(self.graph, self.anchors, endpoints)

    def rim(self) -> DataFrame:
        return rims(self.vicinity, self.radius)


def anchored(g: Graph, alpha: float = 4.0, seed: int = 7, **draw) -> tuple[DataFrame, DataFrame]:
    """Anchors as ``draw_anchors`` gives them, and their radii.

    A component without an anchor is one that the search for the radii does not reach, so only the
    components of nodes it missed are labelled, which are few or none."""
    if draw.get("on_empty", "promote") != "promote":
        anchors = draw_anchors(g, alpha, seed, **draw)
        return anchors, radii(g, anchors)
    anchors = draw_anchors(g, alpha, seed, **(draw | {"on_empty": "whole"}))
    found = radii(g, anchors)
    missed = found.where("r is null").select(F.col("u").alias("src"))
    if missed.isEmpty():
        return anchors, found
    anchors = promoted(g, anchors, component_labels(g.arcs.join(missed, "src", "left_semi").where("src < dst")))
    return anchors, radii(g, anchors)


def build_index(g: Graph, alpha: float = 4.0, seed: int = 7, sources: DataFrame | None = None, tables: bool = False, **draw) -> Index:
    """All parts of the index; ``sources`` (id) restricts vicinities to the endpoints of a batch."""
    anchors, found = anchored(g, alpha, seed, **draw)
    inner = None if g.weighted else inner_arcs(g, found)
    vic = vicinities(g, found, sources, inner=inner)
    index = Index(g, anchors, found, vic, boundaries(g, vic, found))
    if tables:
        index.tables = anchor_tables(g, anchors)
    return index


PARTS = ("nodes", "arcs", "anchors", "radius", "vicinity", "boundary", "tables")
KEYS = {"nodes": "id", "arcs": "src", "anchors": "id", "radius": "u", "vicinity": "u", "boundary": "u", "tables": "a"}


#: Rows of vicinities that a bucket of a saved index is meant to hold, and the fewest buckets.
BUCKET_ROWS, LEAST_BUCKETS = 4_000_000, 16


def save_index(index: Index, folder: str, buckets: int | None = None) -> None:
    """Writes each part as Parquet in directories by bucket of its key, in a folder of its own, then names that folder.

    The manifest is replaced in one step when all parts are there, so readers see the earlier index or
    the new one. The index before is kept for readers that have opened it; older ones are deleted.
    ``buckets`` grows with the vicinities by default."""
    spark = index.graph.arcs.sparkSession
    frames = {"nodes": index.graph.nodes, "arcs": index.graph.arcs, "anchors": index.anchors, "radius": index.radius, "vicinity": index.vicinity, "boundary": index.boundary, "tables": index.tables}
    buckets = buckets or max(LEAST_BUCKETS, -(-index.vicinity.count() // BUCKET_ROWS))
    at, held = f"index-{uuid.uuid4().hex}", []
    for name, df in frames.items():
        if df is None:
            continue
        bucket = F.pmod(F.xxhash64(KEYS[name]), F.lit(buckets)).cast("int")
        rows = df.withColumn("bucket", bucket).repartition(buckets, "bucket").sortWithinPartitions("bucket", KEYS[name])
        rows.write.partitionBy("bucket").parquet(f"{folder}/{at}/{name}")
        held.append(name)
    before = _manifest(spark, folder)
    manifest = {"at": at, "before": before and before["at"], "parts": held, "buckets": buckets, "n": index.graph.n, "m": index.graph.m, "weighted": index.graph.weighted}
    replace_file(spark, f"{folder}/manifest.json", json.dumps(manifest).encode())
    if before and before["before"]:
        delete_folder(spark, f"{folder}/{before['before']}")


def _manifest(spark: SparkSession, folder: str) -> dict | None:
    raw = read_file(spark, f"{folder}/manifest.json")
    return None if raw is None else json.loads(raw)


def read_manifest(spark: SparkSession, folder: str) -> dict:
    """What the saved index consists of; ``at`` is the folder of its parts."""
    found = _manifest(spark, folder)
    if found is None:
        raise FileNotFoundError(f"{folder} holds no index")
    return found


def load_index(spark: SparkSession, folder: str) -> Index:
    """The saved index; its scans prune by the bucket directories. Arcs are bucketed again for searches."""
    about = read_manifest(spark, folder)
    part = {n: spark.read.parquet(f"{folder}/{about['at']}/{n}").drop("bucket") for n in about["parts"]}
    graph = Graph(part["nodes"], bucketed(part["arcs"], "arcs_loaded", "src"), about["n"], about["m"], about["weighted"])
    return Index(graph, part["anchors"], part["radius"], part["vicinity"], part["boundary"], part.get("tables"))
