"""Directed graphs, repair, goal-directed search and edge lists against brute force."""

import itertools
import random

import pytest
from test_engine import asked, distances, ids, make, rows

from pathmeet.operators import baselines, directed, repair, vicinity
from pathmeet.operators.index import build_index
from pathmeet.sources import edgelist

FAR = float("inf")


def one_way(arcs, nodes):
    d = {(a, b): 0 if a == b else 1 if (a, b) in arcs else FAR for a in nodes for b in nodes}
    for k, a, b in itertools.product(nodes, nodes, nodes):
        d[a, b] = min(d[a, b], d[a, k] + d[k, b])
    return d


@pytest.mark.parametrize("seed", range(2))
def test_directed_distances_are_exact_where_answered(spark, seed):
    rng = random.Random(seed)
    arcs = {tuple(rng.sample(range(22), 2)) for _ in range(48)}
    nodes = sorted({x for a in arcs for x in a})
    truth = one_way(arcs, nodes)
    raw = [*arcs, (3, 3), (None, 1), next(iter(arcs))]
    g = directed.build_directed(spark.createDataFrame(raw, "src long, dst long"))
    assert (g.n, g.m) == (len(nodes), len(arcs))
    ix = directed.build_directed_index(g, explicit=ids(spark, *rng.sample(nodes, 3)))
    forward = {r.u: r.r for r in ix.radius_out.collect()}
    backward = {r.u: r.r for r in ix.radius_in.collect()}
    queries = asked(spark, [*itertools.product(nodes, nodes), (nodes[0], 999)])
    seen = set()
    for a in directed.directed_distance(ix, queries).collect():
        seen.add(a.case)
        if a.case == "unknown_node":
            assert a.dist is None and a.t == 999
        elif a.case == "unreachable":
            assert truth[a.s, a.t] == FAR
        elif a.case == "unanswered":
            assert truth[a.s, a.t] >= a.lower == forward[a.s] + backward[a.t] + 1
        else:
            assert a.dist == truth[a.s, a.t]
    assert {"same", "source_anchor", "meet", "unknown_node"} <= seen


@pytest.mark.parametrize("seed", range(2))
def test_repair_equals_a_new_build(spark, seed):
    rng = random.Random(seed)
    pairs = list({tuple(sorted(rng.sample(range(26), 2))) for _ in range(36)})
    old, late = pairs[:-5], [*pairs[-5:], (90, 91), (pairs[0][0], 92), pairs[0], (7, 7)]
    chosen = ids(spark, *sorted({x for p in old for x in p})[:3])
    before = build_index(make(spark, old), explicit=chosen, on_empty="whole")
    after = repair.add_edges(before, spark.createDataFrame(late, "src long, dst long"))
    fresh = build_index(make(spark, old + late), explicit=chosen, on_empty="whole")
    assert (after.graph.n, after.graph.m) == (fresh.graph.n, fresh.graph.m)
    for part, columns in (("radius", ("u", "r", "anchor")), ("vicinity", ("u", "v", "d", "parent", "next_hop", "inside")), ("boundary", ("u", "v", "d"))):
        assert rows(getattr(after, part), *columns) == rows(getattr(fresh, part), *columns), part
    assert repair.add_edges(before, spark.createDataFrame([old[0]], "src long, dst long")) is before


@pytest.mark.parametrize("weighted", [False, True])
def test_goal_directed_search(spark, weighted):
    rng = random.Random(5)
    pairs = list({tuple(sorted(rng.sample(range(18), 2))) for _ in range(26)}) + [(50, 51)]
    costs = [rng.randint(0, 9) for _ in pairs]
    truth = distances(pairs, costs if weighted else None)
    g = make(spark, [(*p, c) for p, c in zip(pairs, costs)] if weighted else pairs, weighted)
    nodes = sorted({x for p in pairs for x in p})
    tables = vicinity.anchor_tables(g, ids(spark, nodes[0], nodes[5], nodes[9]))
    queries = asked(spark, [*list(itertools.product(nodes, nodes))[::5], (nodes[0], 999)])
    for slack in (0, None):
        for a in baselines.astar(g, queries, tables, slack=slack).collect():
            assert (FAR if a.dist is None else a.dist) == truth.get((a.s, a.t), FAR)


def test_edge_list_source_reads_every_line_once(spark, tmp_path):
    pairs = [(i, i * 7919 % 1000) for i in range(500)]
    path = f"{tmp_path}/plain"
    edgelist.write_edge_list(spark.createDataFrame(pairs, "src long, dst long").repartition(3), path)
    (tmp_path / "plain" / "extra").write_text("# comment\n\n5\t6\nbroken\nx\ty\n7 8\n")
    expected = sorted([*pairs, (5, 6), (7, 8)])
    edgelist.register(spark)
    for split in (13, 1000, 1 << 20):
        got = spark.read.format("edgelist").option("split_bytes", split).load(path).collect()
        assert sorted((r.src, r.dst) for r in got) == expected
    assert sorted((r.src, r.dst) for r in edgelist.read_edge_list(spark, path).collect()) == expected
    out = f"{tmp_path}/written"
    rows_in = spark.createDataFrame([(1, 2, 0.5), (2, 3, None)], "src long, dst long, w double")
    for _ in range(2):  # overwriting leaves one copy
        rows_in.write.format("edgelist").option("weighted", "true").mode("overwrite").save(out)
    back = spark.read.format("edgelist").option("weighted", "true").load(out).collect()
    assert sorted((r.src, r.dst, r.w) for r in back) == [(1, 2, 0.5), (2, 3, None)]
