"""Triangles found by triples of colours."""

import random
from collections import Counter
from itertools import combinations

from pathmeet.operators import graph, triangles


def test_triangles_of_any_number_of_colours(spark):
    draw = random.Random(3)
    raw = [(draw.randrange(90) << 45, draw.randrange(90) << 45) for _ in range(1500)] + [(None, 7), (7, None)] + [(i << 45, 1 << 50) for i in range(90)]
    links = {frozenset(e) for e in raw if None not in e and e[0] != e[1]}
    near = {}
    for x, y in map(tuple, links):
        near.setdefault(x, set()).add(y)
        near.setdefault(y, set()).add(x)
    want = Counter(x for x in near for y, z in combinations(near[x], 2) if z in near[y])
    edges = spark.createDataFrame(raw, "src long, dst long")
    for task_links in (100_000, 2400, 300):  # 1, 2 and 6 colours
        assert {r.id: r.triangles for r in triangles.triangle_counts(edges, task_links).collect()} == want
    assert triangles.triangle_counts(spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")).isEmpty()
    assert triangles.triangle_counts(edges.limit(0)).isEmpty()


def test_wedges_are_not_shuffled(spark, monkeypatch):
    """A star of links between two hubs and 300 nodes has 44,850 wedges at each hub; no table written holds as many rows."""
    rows = []
    write = triangles.staged if hasattr(triangles, "staged") else None
    monkeypatch.setattr(triangles, "staged", lambda df, name: (out := write(df, name), rows.append(out.count()))[0])
    g = graph.build_graph(spark.createDataFrame([(h, 10 + i) for h in (1, 2) for i in range(300)] + [(1, 2)], "src long, dst long"))
    assert {r.id: r.triangles for r in graph.triangles(g).collect()} == {1: 300, 2: 300} | {10 + i: 1 for i in range(300)}
    assert max(rows) <= 601
