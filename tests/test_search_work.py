"""Work of the two searches from shared levels, and the table that states it."""

import random

from pathmeet.operators import baselines, shared
from pathmeet.operators.graph import build_graph
from pathmeet.plans import workloads as w


def test_work_of_shared_levels_is_that_of_each_search(spark):
    draw = random.Random(5)
    raw = [(draw.randrange(60), draw.randrange(60)) for _ in range(70)] + [(100 + i, 101 + i) for i in range(5)] + [(200, 200 + i) for i in range(1, 30)]
    g = build_graph(spark.createDataFrame(raw, "src long, dst long"))
    nodes = sorted(r.id for r in g.nodes.collect())
    ends = [(draw.choice(nodes), draw.choice(nodes)) for _ in range(60)] + [(100, 105), (105, 101), (201, 229), (201, 104), (nodes[0], nodes[0]), (100, 999), (999, 100)]
    queries = spark.createDataFrame([(i, s, t) for i, (s, t) in enumerate(ends)], "qid long, s long, t long")
    got = {r.qid: (r.dist, r.bfs_arcs, r.bidirectional_arcs) for r in shared.search_work(g, queries).collect()}
    one = {r.qid: r for r in baselines.bfs_distance(g, queries).collect()}
    two = {r.qid: r for r in baselines.bidirectional_bfs(g, queries).collect()}
    assert got == {q: (one[q].dist, one[q].scanned, two[q].scanned) for q in one}
    assert all(one[q].dist == two[q].dist for q in one) and None in {r.dist for r in one.values()}


def test_cost_table_searches_neither_from_anchors_nor_per_query(spark, sf, monkeypatch):
    answers = w.answers_of(spark, sf, "g_cust_part_r").where("case = 'meet'").orderBy("qid").limit(50)
    ask = w.staged(answers, "expected")
    want = (
        round(sum(r.probes for r in ask.collect()) / ask.count(), 6),
        *(round(sum(r.scanned for r in search(w.graph_of(spark, sf, "g_cust_part_r"), ask.select("qid", "s", "t")).collect()) / ask.count(), 6) for search in (baselines.bfs_distance, baselines.bidirectional_bfs)),
    )

    def refused(*_, **__):
        raise AssertionError("a search per query")

    monkeypatch.setattr(baselines, "bfs_distance", refused)
    monkeypatch.setattr(baselines, "bidirectional_bfs", refused)
    whole = baselines.single_source
    monkeypatch.setattr(baselines, "single_source", lambda g, sources: whole(g, sources) if sources.isEmpty() else refused())
    row = w.cost_table(spark, sf, ("g_cust_part_r",)).first()
    assert (row.mean_probes, row.bfs_arcs, row.bidirectional_arcs) == want
