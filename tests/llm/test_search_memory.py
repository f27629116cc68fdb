"""Memory of the vector search does not depend on how many pairs its bounds leave."""

import tracemalloc

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from pathmeet.llm import vector_search


def given():
    table = pq.read_table("/root/testdata/sf0.1/embeddings.parquet", columns=["vec_id", "embedding"])
    ((ids, v),) = vector_search._matrices(table.combine_chunks().to_batches()[0], 256)
    return ids[:1024], v[:1024], ids[1024:2560], v[1024:2560]


def copies():
    v = given()[1]
    return np.arange(1024) * 50, np.repeat(v[:1], 1024, axis=0), np.arange(1536)[::-1] * 3 + 1, np.repeat(v[:1], 1536, axis=0)


def wide():
    rng = np.random.default_rng(5)
    return np.arange(48) * 50, rng.integers(-256, 257, (48, 2048)).astype(float), np.arange(512) * 50 + 1, rng.integers(-256, 257, (512, 2048)).astype(float)


@pytest.mark.parametrize("made", [given, copies, wide])
def test_pairs_are_gathered_in_slices(made):
    query_ids, q, ids, v = made()
    tracemalloc.start()
    search = vector_search.Search(query_ids, q, 5)
    search.add(ids, v)
    search.reduce()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 100e6
    exact = q.astype(np.int64) @ v.astype(np.int64).T
    expected = {(i, ids[j], exact[i, j]) for i in range(len(q)) for j in np.lexsort((ids, -exact[i]))[:5]}
    got = set(zip(*(x.tolist() for x in search.found), strict=True))
    assert len(search.found[0]) == 5 * len(q) and got == expected


def test_held_candidates_are_bounded_by_bytes():
    rng = np.random.default_rng(6)
    rows = [(i, (rng.integers(-9, 10, 512) / 4).tolist()) for i in range(300)] + [(300 + i, [2.0**e] * 3) for i, e in enumerate((8, 20, 40, 70))] + [(304, [])]
    batch = pa.RecordBatch.from_arrays([pa.array([i for i, _ in rows]), pa.array([x for _, x in rows], pa.list_(pa.float64()))], names=["vec_id", "x"])
    for most in (1 << 16, 1 << 26):
        lists = list(vector_search.gathered(iter([batch.slice(0, 100), batch.slice(100, 101), batch.slice(201)]), 256, 1 << 18, most))
        assert len(lists) == (3 if most == 1 << 16 else 1)
        back = {i: [int(c) for c in row] for some in lists for ids, v in some for i, row in zip(ids.tolist(), v.tolist())}
        assert back == {i: [int(256 * c // 1) for c in x] for i, x in rows}
    assert sum(v.nbytes for _, v in lists[0] if v.shape[1] == 512) == 300 * 512 * 2
