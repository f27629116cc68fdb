"""The grouped kernel against the joins: vicinities, boundaries, and the memory that both engines count."""

import random

from test_engine import make

from pathmeet.functions import kernels
from pathmeet.operators.index import anchored
from pathmeet.operators.vicinity import boundaries, vicinities
from pathmeet.plans import measures


def _graph(spark):
    rng = random.Random(3)
    pairs = {tuple(sorted(rng.sample(range(120), 2))) for _ in range(260)} | {(0, i) for i in range(1, 60)} | {(200, 201), (201, 202)}
    return make(spark, sorted(pairs))


def test_kernel_has_the_members_and_edges_of_the_joins(spark, monkeypatch):
    g = _graph(spark)
    _, radius = anchored(g, 2.0)
    joined = vicinities(g, radius)
    monkeypatch.setattr(kernels, "CELLS", 4 * g.n)  # several groups of sources
    packed = vicinities(g, radius, engine="kernel")
    columns = ["u", "v", "d", "parent", "next_hop", "inside"]
    assert sorted(map(str, packed.select(*columns).collect())) == sorted(map(str, joined.select(*columns).collect()))
    found = sorted(map(tuple, boundaries(g, packed, radius).collect()))
    assert found and found == sorted(map(tuple, boundaries(g, joined, radius).collect()))


def test_slices_of_arcs_change_nothing():
    import numpy as np

    offsets, neighbours = np.array([0, 2, 5, 8, 10, 12]), np.array([1, 2, 0, 2, 3, 0, 1, 4, 1, 4, 2, 3], np.int32)
    args = offsets, neighbours, np.arange(5), np.array([2, 1, 0, 2, -1])
    whole, cut = (kernels.grouped_search(*args, np.zeros(25, np.uint8), most=most) for most in (1 << 20, 1))
    for one, two in zip(whole, cut, strict=True):
        assert one.tolist() == two.tolist()


def test_memory_is_counted_by_the_kernel_as_by_the_joins(spark):
    g = _graph(spark)
    by = [sorted(map(tuple, measures.memory_profile_by_blocks(g, 2.0, block_rows=rows, most_arcs=most).collect())) for rows, most in ((300, 0), (300, 1 << 30))]
    assert by[0] == by[1]
