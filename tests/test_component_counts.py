"""Components are counted with the sizes of a graph, by rounds of joins or by one task at the end."""

import random

import pytest

from pathmeet import components, scratch
from pathmeet.operators import graph
from pathmeet.plans import catalog


@pytest.mark.parametrize("local", [0, 40, 1_000_000])
def test_labels_by_rounds_and_by_one_task(spark, monkeypatch, local):
    monkeypatch.setattr(components, "LOCAL_PAIRS", local)
    rng = random.Random(4)
    pairs = [(rng.randrange(80), rng.randrange(80)) for _ in range(45)] + [(100 + i, 101 + i) for i in range(30)]
    expected = {x: x for pair in pairs for x in pair}
    for _ in expected:
        for a, b in pairs:
            expected[a] = expected[b] = min(expected[a], expected[b])
    edges = spark.createDataFrame(pairs, "src long, dst long")
    assert dict(map(tuple, components.component_labels(edges).collect())) == expected
    if local:
        before = scratch.made()
        linked = {expected[a] for a, b in pairs if a != b}
        assert graph.component_count(edges).first()[0] == len(linked)
        assert len(scratch.made() - before) == 1


def test_stats_have_components(spark):
    raw = [(1, 2), (2, 3), (3, 1), (2, 1), (9, 8), (8, 7), (20, 20), (None, 5), (11, 30)]
    row = catalog._stats_of(spark.createDataFrame(raw, "src long, dst long"), "x").first()
    assert tuple(row) == ("x", 8, 6, 7, 1.5, 2, 3)


def test_nodes_named_by_strings(spark):
    edges = spark.createDataFrame([("b", "a"), ("c", "b"), ("x", "y")], "src string, dst string")
    assert dict(map(tuple, components.component_labels(edges).collect())) == {"a": "a", "b": "a", "c": "a", "x": "x", "y": "x"}
