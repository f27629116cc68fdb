"""Searches in one process on the packed graph, for latency comparison with the serving path."""

from __future__ import annotations

import time

from pathmeet.functions.kernels import packed_graph


def bfs(offsets, neighbours, s: int, t: int) -> int | None:
    seen, level, depth = {s}, [s], 0
    while level:
        if t in seen:
            return depth
        new = []
        for v in level:
            for x in neighbours[offsets[v] : offsets[v + 1]]:
                if x not in seen:
                    seen.add(x)
                    new.append(x)
        level, depth = new, depth + 1
    return None


def bidirectional(offsets, neighbours, s: int, t: int) -> int | None:
    sides = [({s: 0}, [s], 0), ({t: 0}, [t], 0)]
    best = 0 if s == t else None
    while all(level for _, level, _ in sides) and (best is None or sides[0][2] + sides[1][2] < best):
        k = 0 if sum(offsets[v + 1] - offsets[v] for v in sides[0][1]) <= sum(offsets[v + 1] - offsets[v] for v in sides[1][1]) else 1
        (mine, level, depth), (theirs, _, _) = sides[k], sides[1 - k]
        new = []
        for v in level:
            for x in neighbours[offsets[v] : offsets[v + 1]]:
                if x not in mine:
                    mine[x] = depth + 1
                    new.append(x)
                    if x in theirs and (best is None or depth + 1 + theirs[x] < best):
                        best = depth + 1 + theirs[x]
        sides[k] = (mine, new, depth + 1)
    return best


def in_process_searches(g, ends: list[tuple[int, int]]) -> dict[str, float]:
    """Milliseconds per query of both searches over pairs of node ids."""
    ids, offsets, neighbours = packed_graph(g)
    place = {u: i for i, u in enumerate(ids.tolist())}
    offsets, neighbours = offsets.tolist(), neighbours.tolist()
    out = {}
    for name, search in (("single_bfs_ms", bfs), ("single_bidirectional_ms", bidirectional)):
        began = time.perf_counter()
        for s, t in ends:
            search(offsets, neighbours, place[s], place[t])
        out[name] = round(1000 * (time.perf_counter() - began) / max(1, len(ends)), 4)
    return out
