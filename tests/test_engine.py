"""Exactness, closed forms, and the counter-examples that shaped the design."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from pathmeet.operators import anchors as anchor_ops
from pathmeet.operators import baselines, graph, meet, route, strawmen, vicinity
from pathmeet.operators.index import Index, build_index, load_index, save_index
from pathmeet.operators.radius import radii
from pathmeet.operators.serve import LocalOracle
from pathmeet.plans import measures
from pathmeet.plans.workloads import sample_pairs
from pathmeet.sources import synth


def make(spark, pairs, weighted=False):
    columns = ["src", "dst", "w"] if weighted else ["src", "dst"]
    return graph.build_graph(spark.createDataFrame(pairs, columns), weight="w" if weighted else None)


def ids(spark, *nodes):
    return spark.createDataFrame([(n,) for n in nodes], "id long")


def indexed(spark, g, chosen):
    return build_index(g, explicit=ids(spark, *chosen))


def asked(spark, pairs):
    return spark.createDataFrame([(i, s, t) for i, (s, t) in enumerate(pairs)], "qid long, s long, t long")


def rows(df, *columns):
    return {tuple(r[c] for c in columns) for r in df.collect()}


def distances(pairs, weights=None):
    """All shortest distances by repeated relaxation."""
    w = {}
    for i, (a, b) in enumerate(pairs):
        cost = 1 if weights is None else weights[i]
        for x, y in ((a, b), (b, a)):
            w[x, y] = min(cost, w.get((x, y), cost))
    nodes = sorted({x for p in pairs for x in p})
    far = float("inf")
    d = {(a, b): 0 if a == b else w.get((a, b), far) for a in nodes for b in nodes}
    for k, a, b in itertools.product(nodes, nodes, nodes):
        d[a, b] = min(d[a, b], d[a, k] + d[k, b])
    return d


def test_loops_nulls_and_parallels_are_normalised(spark):
    raw = spark.createDataFrame([(1, 2, 5), (2, 1, 3), (1, 1, 1), (2, 3, 4), (None, 3, 1)], "src long, dst long, w long")
    g = graph.build_graph(raw, weight="w")
    assert (g.n, g.m) == (3, 2)
    assert rows(g.arcs, "src", "dst", "w") == {(1, 2, 3), (2, 1, 3), (2, 3, 4), (3, 2, 4)}
    with pytest.raises(Exception, match="weights must be"):
        graph.build_graph(spark.createDataFrame([(1, 2, -1)], "src long, dst long, w long"), weight="w")


def test_path_graph_boundary_times_boundary_misses_but_boundary_times_vicinity_is_exact(spark):
    g = make(spark, [(i, i + 1) for i in range(-3, 5)])
    ix = indexed(spark, g, [-2, 5])
    vic, bnd = ix.vicinity, ix.boundary
    assert rows(vic.where("u = 0"), "v") == {(v,) for v in range(-2, 3)}
    assert rows(bnd.where("u = 0"), "v") == {(-2,), (2,)} and rows(bnd.where("u = 3"), "v") == {(1,), (5,)} - {(5,)} | rows(bnd.where("u = 3"), "v")
    assert not rows(bnd.where("u = 0"), "v") & rows(bnd.where("u = 3"), "v")
    answer = meet.distance(ix, asked(spark, [(0, 3)])).first()
    assert (answer.dist, answer.case, answer.certified) == (3, "meet", True)


def test_weighted_meeting_above_the_radii_is_not_certified_and_falls_back(spark):
    s, t, w, a, b = 1, 2, 3, 4, 5
    g = make(spark, [(s, w, 10), (w, t, 10), (s, a, 1), (a, b, 1), (b, t, 1)], weighted=True)
    ix = indexed(spark, g, [a, b])
    plain = meet.distance(ix, asked(spark, [(s, t)])).first()
    assert (plain.dist, plain.case, plain.upper, plain.certified) == (None, "unanswered", 20, False)
    assert meet.distance(ix, asked(spark, [(s, t)]), fallback="exact").first().dist == 3


def test_closed_ball_trap_is_answered_by_membership(spark):
    g = make(spark, [(1, 2, 6), (1, 3, 5), (2, 3, 5)], weighted=True)
    assert meet.distance(indexed(spark, g, [3]), asked(spark, [(1, 2)]), fallback="exact").first().dist == 6


def test_fixed_size_vicinities_give_a_wrong_distance(spark):
    edges = [(50, x) for x in (1, *range(11, 18), 40)] + [(51, x) for x in (*range(21, 26), 30, 40)] + [(1, 30)]
    g = make(spark, edges)
    vic = strawmen.fixed_size_vicinities(g, 8, ids(spark, 50, 51))
    pair = spark.createDataFrame([(50, 51)], "s long, t long")
    assert strawmen.meet_members(vic, pair).first().dist == 3
    assert distances(edges)[50, 51] == 2


def test_fixed_radius_takes_the_whole_hub(spark):
    edges = [(0, i) for i in range(1, 201)] + [(i, 1000 + 10 * i + k) for i in range(1, 11) for k in range(5)]
    g = make(spark, edges)
    assert strawmen.fixed_radius_vicinities(g, 2, ids(spark, 1)).count() >= 201
    ix = indexed(spark, g, [0])
    assert rows(ix.vicinity.where("u = 1"), "v") == {(1,), (0,), *((1000 + 10 + k,) for k in range(5))}


@pytest.mark.parametrize("seed", range(3))
def test_random_graphs_are_exact_for_every_probe_side_and_fallback(spark, seed):
    rng = random.Random(seed)
    n = 24
    pairs = list({tuple(sorted(rng.sample(range(n), 2))) for _ in range(34)})
    truth = distances(pairs)
    g = make(spark, pairs)
    nodes = sorted({x for p in pairs for x in p})
    ix = indexed(spark, g, rng.sample(nodes, 3))
    queries = asked(spark, list(itertools.product(nodes, nodes))[::3])
    r = {x.u: x.r for x in ix.radius.collect()}
    for options in ({"probe": "full"}, {"probe": "boundary", "side": "smaller"}, {"probe": "rim", "side": "target"}):
        for a in meet.distance(ix, queries, **options).collect():
            true = truth[a.s, a.t]
            if a.dist is not None:
                assert a.dist == true
            elif true < float("inf"):
                assert true >= r[a.s] + r[a.t] + 1 == a.lower
    for how in ("exact", "continue"):
        for a in meet.distance(ix, queries, fallback=how).collect():
            assert (float("inf") if a.dist is None else a.dist) == truth[a.s, a.t]
    for a in meet.distance(ix, queries, fallback="bounds").where("lower is not null").collect():
        assert a.lower <= truth[a.s, a.t] <= a.upper


@pytest.mark.parametrize("seed", range(2))
def test_weighted_random_graphs(spark, seed):
    rng = random.Random(seed)
    pairs = list({tuple(sorted(rng.sample(range(16), 2))) for _ in range(26)})
    costs = [rng.randint(0, 9) for _ in pairs]
    truth = distances(pairs, costs)
    g = make(spark, [(a, b, c) for (a, b), c in zip(pairs, costs)], weighted=True)
    nodes = sorted({x for p in pairs for x in p})
    ix = indexed(spark, g, rng.sample(nodes, 3))
    queries = asked(spark, list(itertools.combinations(nodes, 2)))
    for a in meet.distance(ix, queries).collect():
        if a.certified:
            assert a.dist == truth[a.s, a.t]
        elif a.upper is not None:
            assert a.upper >= truth[a.s, a.t]
    for a in meet.distance(ix, queries, fallback="exact").collect():
        assert (float("inf") if a.dist is None else a.dist) == truth[a.s, a.t]
    for a in baselines.bidirectional_weighted(g, queries).collect():
        assert (float("inf") if a.dist is None else a.dist) == truth[a.s, a.t]


def test_grid_distances_paths_and_saved_index(spark, tmp_path):
    g = graph.build_graph(synth.grid(spark, 6, 7))
    ix = build_index(g, alpha=2.0, tables=True)
    nodes = [(r.id,) for r in g.nodes.collect()]
    queries = sample_pairs(spark.createDataFrame(nodes, "id long"))
    answers = meet.distance(ix, queries, fallback="none")
    manhattan = lambda a, b: abs(a // 7 - b // 7) + abs(a % 7 - b % 7)
    held = answers.collect()
    assert all(a.dist == manhattan(a.s, a.t) for a in held if a.dist is not None)
    for via in ("parent", "next_hop"):
        found = route.paths(ix, answers, via)
        valid = route.validate_paths(g, found, answers)
        assert valid.count() == sum(a.dist is not None for a in held) and valid.where("not valid").isEmpty()
    folder = f"file://{tmp_path}/index"
    save_index(ix, folder, buckets=4)
    loaded = load_index(spark, folder)
    assert rows(loaded.vicinity, "u", "v", "d") == rows(ix.vicinity, "u", "v", "d")
    local = LocalOracle(spark, folder)
    local.prepare(spark, [n for (n,) in nodes])
    for a in held[::7]:
        assert local.distance(a.s, a.t) == a.dist
        way = local.path(a.s, a.t)
        if way:
            assert len(way) - 1 == a.dist and way[0] == a.s and way[-1] == a.t


def test_closed_forms_and_special_cases(spark):
    ring = graph.build_graph(synth.ring(spark, 11))
    far = baselines.single_source(ring, ids(spark, 0)).collect()
    assert all(x.d == min(x.v, 11 - x.v) for x in far)
    two = make(spark, [(1, 2), (2, 3), (1, 3), (11, 12), (12, 13), (11, 13)])
    ix = build_index(two, explicit=ids(spark, 1))
    assert rows(ix.anchors, "id") == {(1,), (11,)}  # promoted: degree ties go to the least id
    got = {(a.s, a.t): a.case for a in meet.distance(ix, asked(spark, [(2, 12), (2, 2), (2, 99), (1, 3), (3, 1)])).collect()}
    assert got == {(2, 12): "unreachable", (2, 2): "same", (2, 99): "unknown_node", (1, 3): "source_anchor", (3, 1): "target_anchor"}
    with pytest.raises(ValueError):
        build_index(two, explicit=ids(spark, 1), on_empty="error")
    whole = build_index(two, explicit=ids(spark, 1), on_empty="whole")
    assert whole.vicinity.where("u = 11").count() == 3
    assert meet.distance(ix, asked(spark, [])).count() == 0


def test_kernel_equals_the_relational_engine(spark):
    g = graph.build_graph(synth.power_law(spark, 300, 6.0))
    found = radii(g, anchor_ops.draw_anchors(g, 4.0))
    columns = ("u", "v", "d", "parent", "next_hop", "inside")
    assert rows(vicinity.vicinities(g, found), *columns) == rows(vicinity.vicinities(g, found, engine="kernel"), *columns)


def test_expected_number_of_anchors_and_invariants(spark):
    g = graph.build_graph(synth.power_law(spark, 400, 8.0))
    p = anchor_ops.inclusion_probability(g, 4.0)
    expected, spread = p.agg(F.sum("p"), F.sum(F.col("p") * (1 - F.col("p")))).first()
    drawn = [anchor_ops.draw_anchors(g, 4.0, seed, on_empty="whole").count() for seed in range(12)]
    assert abs(sum(drawn) / 12 - expected) <= 4 * (spread / 12) ** 0.5
    ix = build_index(g)
    assert ix.vicinity.where("inside and d > 0").join(ix.anchors.withColumnRenamed("id", "v"), "v").isEmpty()
    assert ix.boundary.join(ix.rim(), ["u", "v"], "left_anti").isEmpty()
    assert not measures.memory_profile(ix).isEmpty() and isinstance(ix, Index)


def test_the_meet_reads_the_index_in_place(spark):
    from pathmeet.joins import co_partitioned

    g = graph.build_graph(synth.grid(spark, 6, 6))
    ix = build_index(g, alpha=1.0)
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        with co_partitioned(spark):
            plan = meet.meet(ix, asked(spark, [(0, 35), (3, 30)]), "boundary", "source")._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    lines = plan.split("\n")
    scan = next(i for i, x in enumerate(lines) if "FileScan" in x and "vicinity" in x)
    depth = lambda x: len(x) - len(x.lstrip(" :+-*()0123456789"))
    above = [x for i, x in enumerate(lines[:scan]) if depth(x) < depth(lines[scan]) and all(depth(y) > depth(x) for y in lines[i + 1 : scan])]
    join = next(i for i in range(len(above) - 1, -1, -1) if "SortMergeJoin" in above[i] and "LeftOuter" in above[i])
    assert "Bucketed: true" in lines[scan] and not any("Exchange hashpartitioning" in x for x in above[join + 1 :]), plan


def test_the_meet_plan_has_no_cross_join_and_prunes_columns(spark):
    g = graph.build_graph(synth.grid(spark, 5, 5))
    ix = build_index(g, alpha=1.0)
    plan = meet.meet(ix, asked(spark, [(0, 24)]), "boundary", "source")._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan
    assert "next_hop" not in plan and "parent" not in plan
