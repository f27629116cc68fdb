"""The memory of an index that is built block by block."""

from test_engine import make

from pathmeet.operators.index import build_index
from pathmeet.plans import measures


def test_memory_by_blocks_is_that_of_the_whole_index(spark):
    pairs = [(i, (i * 7 + k) % 60) for i in range(60) for k in (1, 5) if i != (i * 7 + k) % 60]
    g = make(spark, pairs)
    expected = sorted(map(tuple, measures.memory_profile(build_index(g, 1.0)).collect()))
    assert sorted(map(tuple, measures.memory_profile_by_blocks(g, 1.0, block_rows=200).collect())) == expected
