"""The reported experiments on one packed graph: coverage, radii, boundaries and cost per setting.

A setting is an (alpha, repeat); settings are rows, and each is measured whole by one task on the packed graph,
which executors get once each. The numbers are those of the relational engine: the same draws,
radii, vicinities and boundaries (a test compares them). Graphs beyond the kernel's limit are
measured with ``plans.workloads`` instead."""

from __future__ import annotations

import hashlib
import math
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from pathmeet.functions.kernels import truncated_search
from pathmeet.functions.searches import bfs, bidirectional

MEASURES = (
    "n long, m long, alpha double, rep int, anchors long, mean_radius double, mean_vicinity double, worst_boundary double, pairs long, open_pairs long, meeting long, "
    "answered long, wrong long, mean_lookups double, worst_lookups long"
)
COSTS = "lookup_us double, query_ms double, bfs_ms double, bidirectional_ms double, bfs_arcs double, bidirectional_arcs double"


def draw(text: str, digits: int = 8) -> float:
    return int(hashlib.md5(text.encode()).hexdigest()[:digits], 16) / 16.0**digits


def distances_from(offsets: np.ndarray, neighbours: np.ndarray, sources: np.ndarray) -> np.ndarray:
    """Steps from the nearest source, -1 where none is reached."""
    dist = np.full(len(offsets) - 1, -1)
    dist[sources] = 0
    level, depth = sources, 0
    while len(level):
        depth += 1
        sizes = offsets[level + 1] - offsets[level]
        at = np.repeat(offsets[level] - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(sizes.sum())
        level = np.unique(neighbours[at])
        level = level[dist[level] < 0]
        dist[level] = depth
    return dist


def anchors_of(ids: np.ndarray, degree: np.ndarray, alpha: float, seed: int) -> np.ndarray:
    """Positions of the drawn anchors, by the literal probabilities."""
    n, m = len(ids), int(degree.sum()) // 2
    steps = (2 * n * degree + m - 1) // m
    p = np.minimum(1.0, m / (alpha * n * math.sqrt(n)) * steps)
    draws = np.fromiter((draw(f"{i}:{seed}") for i in ids.tolist()), float, n)
    return np.flatnonzero(draws < p)


def promoted(offsets: np.ndarray, neighbours: np.ndarray, degree: np.ndarray, anchors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Anchors with the node of highest degree of every component that has none, and all radii."""
    dist = distances_from(offsets, neighbours, anchors)
    while (dist < 0).any():
        lost = np.flatnonzero(dist < 0)
        inside = distances_from(offsets, neighbours, lost[:1]) >= 0
        best = np.flatnonzero(inside)
        anchors = np.append(anchors, best[np.argmax(degree[best])])
        dist = distances_from(offsets, neighbours, anchors)
    return np.sort(anchors), dist


def sample_of(ids: np.ndarray, rep: int, size: int) -> np.ndarray:
    """Positions of the sample of a repeat: the least md5("rep:id")."""
    return np.array(sorted(range(len(ids)), key=lambda i: (hashlib.md5(f"{rep}:{ids[i]}".encode()).hexdigest(), ids[i]))[:size])


def measured(graph: tuple, alpha: float, rep: int, size: int, seed: int, timed: int) -> dict:
    """One setting: vicinities of a sample are materialised and intersected pair by pair."""
    ids, offsets, neighbours = graph
    degree = np.diff(offsets)
    anchors, radius = promoted(offsets, neighbours, degree, anchors_of(ids, degree, alpha, seed + rep))
    is_anchor = np.zeros(len(ids), bool)
    is_anchor[anchors] = True
    chosen = sorted(sample_of(ids, rep, size).tolist())
    members, edges, exact = {}, {}, {}
    for u in chosen:
        v, d, _, _ = truncated_search(offsets, neighbours, u, int(radius[u]))
        held = dict(zip(v.tolist(), d.tolist(), strict=True))
        members[u] = held
        inside = np.zeros(len(ids), bool)
        inside[v] = True
        rim = v[d == radius[u]] if radius[u] > 0 else v[:0]
        edges[u] = [(x, held[x]) for x in rim.tolist() if not inside[neighbours[offsets[x] : offsets[x + 1]]].all()]
        exact[u] = distances_from(offsets, neighbours, np.array([u]))
    pairs = [(s, t) for i, s in enumerate(chosen) for t in chosen[i + 1 :]]
    lookups, meeting, answered, wrong, open_pairs, met = [], 0, 0, 0, 0, []
    began = time.perf_counter()
    for s, t in pairs:
        theirs, best, probes = members[t], None, 4
        if is_anchor[s] or is_anchor[t]:
            best = int(exact[s][t]) if exact[s][t] >= 0 else None
            answered += 1
            continue
        open_pairs += 1
        if t in members[s]:
            best = members[s][t]
        elif s in theirs:
            best = theirs[s]
        else:
            for x, d in edges[s]:
                other = theirs.get(x)
                if other is not None and (best is None or d + other < best):
                    best = d + other
            probes += len(edges[s])
            lookups.append(probes)
            if best is not None:
                met.append((s, t))
        if best is not None:
            meeting += 1
            wrong += best != exact[s][t]
        answered += best is not None or exact[s][t] < 0
    spent = time.perf_counter() - began
    out = {
        "n": len(ids), "m": int(degree.sum()) // 2, "alpha": alpha, "rep": rep, "anchors": len(anchors), "mean_radius": float(radius.mean()),
        "mean_vicinity": float(np.mean([len(x) for x in members.values()])), "worst_boundary": max(map(len, edges.values()), default=0) / len(ids),
        "pairs": len(pairs), "open_pairs": open_pairs, "meeting": meeting, "answered": answered, "wrong": wrong,
        "mean_lookups": float(np.mean(lookups)) if lookups else None, "worst_lookups": max(lookups, default=None),
    }
    if timed and met:
        plain_offsets, plain_neighbours = offsets.tolist(), neighbours.tolist()
        some = met[:: max(1, len(met) // timed)][:timed]
        clock = {}
        for name, search in (("bfs", bfs), ("bidirectional", bidirectional)):
            start = time.perf_counter()
            for s, t in some:
                search(plain_offsets, plain_neighbours, s, t)
            clock[name] = (time.perf_counter() - start) / len(some)
        start = time.perf_counter()
        for s, t in some:
            theirs = members[t]
            min((d + theirs[x] for x, d in edges[s] if x in theirs), default=None)
        one = (time.perf_counter() - start) / len(some)
        arcs = np.mean([degree[exact[s] < exact[s][t]][exact[s][exact[s] < exact[s][t]] >= 0].sum() for s, t in some])
        out |= {"query_ms": 1000 * one, "lookup_us": 1e6 * spent / max(1, sum(lookups)), "bfs_ms": 1000 * clock["bfs"], "bidirectional_ms": 1000 * clock["bidirectional"], "bfs_arcs": float(arcs), "bidirectional_arcs": None}
    return out


def experiment(spark: SparkSession, graph: tuple, settings: list[tuple[float, int]], size: int, seed: int = 7, timed: int = 0) -> DataFrame:
    """One row of measures per setting; ``timed`` queries of each are also timed with three methods."""
    held = spark.sparkContext.broadcast(graph)
    kind = MEASURES + (", " + COSTS if timed else "")
    names = [x.split()[0] for x in kind.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = {"double": pa.float64(), "long": pa.int64(), "int": pa.int32()}
        schema = pa.schema([(x.split()[0], types[x.split()[1]]) for x in kind.split(", ")])
        for batch in batches:
            for alpha, rep in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                row = measured(held.value, alpha, rep, size, seed, timed)
                yield pa.RecordBatch.from_pylist([{n: row.get(n) for n in names}], schema=schema)

    rows = spark.createDataFrame(settings, "alpha double, rep int").repartition(len(settings))
    return rows.mapInArrow(run, kind)
