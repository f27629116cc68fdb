"""Searches that share the labels of an endpoint, and bounds without whole anchor tables, against brute force."""

import itertools
import random

import pytest
from test_engine import asked, distances, ids, make

from pathmeet.operators import endpoints, fallback, meet, vicinity
from pathmeet.operators.index import Index, build_index

FAR = float("inf")


def _graph(spark, weighted, seed=5):
    rng = random.Random(seed)
    pairs = list({tuple(sorted(rng.sample(range(30), 2))) for _ in range(44)}) + [(50, 51), (51, 52), (52, 53)]
    costs = [rng.randint(0, 9) for _ in pairs]
    truth = distances(pairs, costs if weighted else None)
    return make(spark, [(*p, c) for p, c in zip(pairs, costs)] if weighted else pairs, weighted), sorted({x for p in pairs for x in p}), truth


@pytest.mark.parametrize("weighted", [False, True])
def test_goal_directed_search_shares_the_labels_of_a_source(spark, monkeypatch, weighted):
    g, nodes, truth = _graph(spark, weighted)
    monkeypatch.setattr(endpoints, "MOST_QUERIES", 100)  # more than one block
    queries = asked(spark, [*list(itertools.product(nodes, nodes))[::8], (nodes[0], 999)])
    found = endpoints.goal_directed_distance(g, queries, vicinity.anchor_tables(g, ids(spark, nodes[0], nodes[5], nodes[9]))).collect()
    assert len(found) == queries.count()
    for a in found:
        assert (FAR if a.dist is None else a.dist) == truth.get((a.s, a.t), FAR), a


@pytest.mark.parametrize("seed", [1])
def test_two_sided_weighted_search_shares_the_labels_of_an_endpoint(spark, monkeypatch, seed):
    g, nodes, truth = _graph(spark, True, seed)
    monkeypatch.setattr(endpoints, "MOST_QUERIES", 1000)
    queries = asked(spark, [*list(itertools.product(nodes, nodes))[::2], (nodes[0], 999)])
    found = endpoints.bidirectional_weighted_distance(g, queries).collect()
    assert len(found) == queries.count()
    for a in found:
        assert (FAR if a.dist is None else a.dist) == truth.get((a.s, a.t), FAR), a


def test_bounds_search_for_the_pairs_only(spark, monkeypatch):
    line = [(i, i + 1) for i in range(12)]
    truth = distances(line, None)
    ix = build_index(make(spark, line), explicit=ids(spark, 1, 6, 11))
    answers = meet.distance(ix, asked(spark, list(itertools.combinations(range(13), 2)))).localCheckpoint()
    monkeypatch.setattr(Index, "anchor_dist", lambda *_: pytest.fail("whole tables were built"))
    found = [r for r in fallback.bounds(ix, answers).collect() if r.case in ("bounds", "bounds_exact")]
    assert found
    assert all(r.lower <= truth[r.s, r.t] <= r.upper for r in found)
