"""Sizes of a graph that leave nothing of it on disk."""

from pathmeet import scratch
from pathmeet.operators import graph


def test_sizes_of_a_graph_that_is_not_built(spark):
    raw = [(1, 2), (2, 1), (1, 2), (2, 3), (4, 4), (None, 5), (5, None), (7, 6)]
    before = scratch.made()
    row = graph.sizes(spark.createDataFrame(raw, "src long, dst long")).first()
    assert tuple(row) == (5, 3, 4, 1.2, 2)
    assert scratch.made() == before
    assert tuple(graph.sizes(spark.createDataFrame([], "src long, dst long")).first())[:3] == (0, 0, 0)
