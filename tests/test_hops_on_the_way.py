"""Paths by first steps from an index of the endpoints only."""

import itertools
import random

from test_engine import asked, distances, ids, make

from pathmeet import scratch
from pathmeet.operators import meet, route
from pathmeet.operators.index import build_index


def test_first_steps_need_no_index_of_every_node(spark):
    rng = random.Random(2)
    pairs = sorted({tuple(sorted(rng.sample(range(60), 2))) for _ in range(70)} | {(i, i + 1) for i in range(59)})
    g, truth = make(spark, pairs), distances(pairs, None)
    ends = list(range(0, 60, 3))
    ix = build_index(g, explicit=ids(spark, 5, 41), sources=ids(spark, *ends))
    answers = meet.distance(ix, asked(spark, list(itertools.product(ends, ends)))).localCheckpoint()
    expected = {r.qid: (r.s, r.t) for r in answers.collect() if r.dist is not None}
    before = scratch.made()
    found = {r.qid: r.path for r in route.paths(ix, answers, "next_hop").collect()}
    assert found.keys() == expected.keys() and any(len(p) > 5 for p in found.values())
    links = {*pairs, *((b, a) for a, b in pairs)}
    for qid, (s, t) in expected.items():
        path = found[qid]
        assert (path[0], path[-1], len(path) - 1) == (s, t, truth[s, t])
        assert all(step in links for step in itertools.pairwise(path))
    assert not any("vicinity" in path for path in scratch.made() - before)  # tables built on the way are gone
