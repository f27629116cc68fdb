"""Connected components by contraction: hook every label to its least neighbour, compress, relabel."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.scratch import discard, staged

#: Edges, counted in both directions, that one task contracts in memory.
LOCAL_PAIRS = 1_000_000


def component_labels(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """(id, comp) for every node of ``edges``; ``comp`` is the least id of its component.

    Each round sends every label to the least label next to it (a forest, since targets
    are smaller), shortens the chains by pointer jumping, and replaces edges by those
    between different labels. Aggregations are minima, so a node with very many edges is
    combined before the shuffle; rounds are cut by written tables. At most ``LOCAL_PAIRS`` edges
    that are left, of nodes named by long integers, are contracted to the end by one task."""
    pairs = edges.select(F.col(src).alias("a"), F.col(dst).alias("b"))
    live = staged(pairs.where("a <> b").union(pairs.where("a <> b").select("b", "a")).distinct(), "cc-edges")
    plain = pairs.schema["a"].dataType.simpleString() == "bigint" == pairs.schema["b"].dataType.simpleString()
    loops = pairs.select("a").union(pairs.select("b")).distinct()
    labels = staged(loops.select(F.col("a").alias("id"), F.col("a").alias("comp")), "cc-labels")
    while (left := live.count()) > 0:
        if plain and left <= LOCAL_PAIRS:
            roots = staged(live.coalesce(1).mapInArrow(_rooted, "x long, to long"), "cc-roots")
            return staged(labels.join(roots.withColumnRenamed("x", "comp"), "comp", "left").select("id", F.coalesce("to", "comp").alias("comp")), "cc-labels")
        hooks = live.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("x"), F.least("a", "m").alias("to"))
        hooks = _compressed(staged(hooks, "cc-hooks"))
        one, two = (hooks.select(F.col("x").alias(k), F.col("to").alias(f"{k}_to")) for k in ("a", "b"))
        moved = live.join(one, "a").join(two, "b").select(F.col("a_to").alias("a"), F.col("b_to").alias("b")).where("a <> b").distinct()
        ahead = labels.join(hooks.withColumnRenamed("x", "comp"), "comp", "left").select("id", F.coalesce("to", "comp").alias("comp"))
        before, live, labels_before, labels = live, staged(moved, "cc-edges"), labels, staged(ahead, "cc-labels")
        for done in (before, labels_before, hooks):
            discard(done)
    return labels


def _rooted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(x, to): the least node of each node's component, by the same hooks and jumps on arrays."""
    pairs = [(batch.column(0).to_numpy(), batch.column(1).to_numpy()) for batch in batches]
    if not pairs:
        return
    ids, places = np.unique(np.concatenate([np.concatenate(c) for c in zip(*pairs, strict=True)]), return_inverse=True)
    a, b = np.split(places, 2)
    to = np.arange(len(ids))
    while True:
        least = np.minimum(to[a], to[b])
        np.minimum.at(to, to[a], least)
        np.minimum.at(to, to[b], least)
        while not np.array_equal(up := to[to], to):
            to = up
        if np.array_equal(to[a], to[b]):
            break
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[to])], names=["x", "to"])


def _compressed(hooks: DataFrame) -> DataFrame:
    """Pointer jumping until every entry points to a root."""
    while True:
        up = hooks.select(F.col("x").alias("to"), F.col("to").alias("up"))
        jumped = staged(hooks.join(up, "to").select("x", F.col("up").alias("to"), (F.col("up") < F.col("to")).alias("moved")), "cc-jump")
        discard(hooks)
        moved = not jumped.where("moved").isEmpty()
        hooks = jumped.select("x", "to")
        if not moved:
            return hooks
