"""Arrow kernels: truncated searches on a packed graph, sorted-array meets, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Arcs that a packed graph may have to be shipped to every executor (16 bytes each).
MOST_ARCS = 50_000_000


def packed_graph(g) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Node ids, offsets and neighbour positions in compressed rows; refused beyond ``MOST_ARCS``.

    Spark sorts the arcs, so the driver gets one column of them."""
    if 2 * g.m > MOST_ARCS:
        raise ValueError(f"{2 * g.m} arcs: the kernel ships graphs of up to {MOST_ARCS}; use the relational engine")
    nodes = g.nodes.orderBy("id").select("id", "deg").toArrow()
    ids = nodes.column("id").to_numpy()
    offsets = np.append(0, np.cumsum(nodes.column("deg").to_numpy()))
    ends = g.arcs.orderBy("src", "dst").select("dst").toArrow().column("dst")
    neighbours = np.concatenate([np.searchsorted(ids, c.to_numpy()).astype(np.int32) for c in ends.chunks] or [np.zeros(0, np.int32)])
    return ids, offsets, neighbours


def truncated_search(offsets: np.ndarray, neighbours: np.ndarray, source: int, radius: int | None) -> tuple[np.ndarray, ...]:
    """Members, distances, parents and first steps of one vicinity, by positions."""
    place = {source: 0}
    members, dist, parent, first = [source], [0], [-1], [-1]
    level, depth = [source], 0
    while level and (radius is None or depth < radius):
        depth += 1
        new: dict[int, tuple[int, int]] = {}
        for v in level:
            hop = first[place[v]]
            for x in neighbours[offsets[v] : offsets[v + 1]].tolist():
                if x not in place:
                    step = x if hop < 0 else hop
                    old = new.get(x)
                    new[x] = (v, step) if old is None else (min(old[0], v), min(old[1], step))
        level = sorted(new)
        for x in level:
            place[x] = len(members)
            members.append(x)
            dist.append(depth)
            parent.append(new[x][0])
            first.append(new[x][1])
    return tuple(np.array(a, np.int64) for a in (members, dist, parent, first))


#: Cells of the table that marks the members of all sources of a group, one byte each; at least one source fits.
CELLS = 1 << 24


def _around(offsets: np.ndarray, neighbours: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For every arc of the nodes ``v``: the row of its node, and its other end."""
    begin, deg = offsets[v], offsets[v + 1] - offsets[v]
    row = np.repeat(np.arange(len(v)), deg)
    return row, neighbours[np.arange(len(row)) - np.repeat(np.cumsum(deg) - deg, deg) + begin[row]]


def _slices(cost: np.ndarray, most: int) -> Iterator[slice]:
    """Runs of rows whose costs sum to about ``most`` at most; a row alone may cost more."""
    run = np.cumsum(cost) // most
    cuts = np.flatnonzero(np.diff(run)) + 1
    for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(cost)], strict=True):
        if a < b:
            yield slice(a, b)


def grouped_search(offsets: np.ndarray, neighbours: np.ndarray, sources: np.ndarray, radius: np.ndarray, mark: np.ndarray, most: int = 1 << 21) -> tuple[np.ndarray, ...]:
    """Vicinities of a group of sources at once: (source's row, member, distance, parent, first step, edge), by positions.

    ``radius`` is -1 where a component has no anchor. ``mark`` has a cell for each source and node, 0 before and
    after. ``edge`` tells the members at the radius that have a neighbour outside of the vicinity."""
    n = len(offsets) - 1
    none = np.full(len(sources), -1, np.int64)
    level = (np.arange(len(sources)), sources.astype(np.int64), none, none)
    mark[level[0] * n + level[1]] = 1
    held, depth = [(*level, 0)], 0
    while True:
        bounded = radius[level[0]]
        grow = (bounded < 0) | (depth < bounded)
        row, v, _, hop = (x[grow] for x in level)
        depth += 1
        parts = []
        for some in _slices(offsets[v + 1] - offsets[v], most):
            at, x = _around(offsets, neighbours, v[some])
            key = row[some][at] * n + x
            new = mark[key] == 0
            at, x, key = at[new], x[new].astype(np.int64), key[new]
            order = np.argsort(key, kind="stable")
            key, at, x = key[order], at[order], x[order]
            first = np.flatnonzero(np.diff(key, prepend=-1))
            if len(first):
                before = v[some][at]
                step = np.where(hop[some][at] < 0, x, hop[some][at])
                parts.append((key[first], np.minimum.reduceat(before, first), np.minimum.reduceat(step, first)))
        if not parts:
            break
        key, parent, step = (np.concatenate(c) for c in zip(*parts, strict=True))
        if len(parts) > 1:  # a member can be reached from several slices
            order = np.argsort(key, kind="stable")
            first = np.flatnonzero(np.diff(key[order], prepend=-1))
            key, parent, step = key[order][first], np.minimum.reduceat(parent[order], first), np.minimum.reduceat(step[order], first)
        mark[key] = 1
        level = (key // n, key % n, parent, step)
        held.append((*level, depth))
    row, v, parent, step = (np.concatenate([h[i] for h in held]) for i in range(4))
    d = np.concatenate([np.full(len(h[0]), h[4], np.int64) for h in held])
    deg, size = offsets[v + 1] - offsets[v], np.bincount(row, minlength=len(sources))
    rim = (radius[row] > 0) & (d == radius[row])
    edge = rim & (deg >= size[row])
    left = np.flatnonzero(rim & ~edge)
    for some in _slices(deg[left], most):
        rows = left[some]
        at, x = _around(offsets, neighbours, v[rows])
        edge[rows[at[mark[row[rows][at] * n + x] == 0]]] = True
    mark[row * n + v] = 0
    return row, v, d, parent, step, edge


def kernel_vicinities(g, start: DataFrame) -> DataFrame:
    """Vicinities by truncated searches on the packed graph, many sources at once, without a shuffle of rows.

    The packed graph reaches executors as a broadcast, once each, and serves all calls. ``edge`` marks the boundary."""
    spark = start.sparkSession
    if "packed" not in g.memo:
        g.memo["packed"] = spark.sparkContext.broadcast(packed_graph(g))
    held = g.memo["packed"]
    kind = "u long, v long, d long, parent long, next_hop long, inside boolean, edge boolean"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, offsets, neighbours = held.value
        group = max(1, CELLS // max(1, len(ids)))
        mark = np.zeros(group * len(ids), np.uint8)

        def named(a: np.ndarray) -> pa.Array:
            return pa.array(ids[np.maximum(a, 0)], pa.int64(), mask=a < 0)

        for batch in batches:
            places = np.searchsorted(ids, batch.column(0).to_numpy())
            bounds = batch.column(1).fill_null(-1).to_numpy()
            for first in range(0, len(places), group):
                sources, radius = places[first : first + group], bounds[first : first + group]
                row, v, d, parent, step, edge = grouped_search(offsets, neighbours, sources, radius, mark)
                inside = (radius[row] < 0) | (d < radius[row])
                yield pa.RecordBatch.from_arrays([pa.array(ids[sources[row]]), pa.array(ids[v]), pa.array(d), named(parent), named(step), pa.array(inside), pa.array(edge)], names=["u", "v", "d", "parent", "next_hop", "inside", "edge"])

    return start.select("u", "r").mapInArrow(run, kind)


def meet_packed(own: str, other: str):
    """Column (dist, witness, probes) of two packed arrays of (v, d) sorted by v: the serving form of a meet."""

    @F.arrow_udf(T.StructType([T.StructField("dist", T.LongType()), T.StructField("witness", T.LongType()), T.StructField("probes", T.LongType())]))
    def meet(a: pa.Array, b: pa.Array) -> pa.Array:
        out = []
        for x, y in zip(a.to_pylist(), b.to_pylist(), strict=True):
            if not x or not y:
                out.append({"dist": None, "witness": None, "probes": len(x or ())})
                continue
            av, ad = (np.fromiter((p[k] for p in x), np.int64, len(x)) for k in ("v", "d"))
            bv, bd = (np.fromiter((p[k] for p in y), np.int64, len(y)) for k in ("v", "d"))
            at = np.searchsorted(bv, av)
            hit = np.flatnonzero(np.append(bv, -1)[np.minimum(at, len(bv))] == av)
            if not len(hit):
                out.append({"dist": None, "witness": None, "probes": len(av)})
                continue
            total = ad[hit] + bd[at[hit]]
            best = np.lexsort((av[hit], total))[0]
            out.append({"dist": int(total[best]), "witness": int(av[hit][best]), "probes": len(av)})
        return pa.array(out, pa.struct([("dist", pa.int64()), ("witness", pa.int64()), ("probes", pa.int64())]))

    return meet(F.col(own), F.col(other))


def register_table_functions(spark) -> None:
    """SQL table function ``path_nodes(path)``: (pos, node) of a path."""

    @F.udtf(returnType="pos int, node bigint")
    class PathNodes:
        def eval(self, path):
            yield from enumerate(path or ())

    spark.udtf.register("path_nodes", PathNodes)
