"""The experiment kernel against the relational engine, saved indexes, and sources of bounded tasks."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathmeet import scratch
from pathmeet.functions.experiment import experiment, measured
from pathmeet.functions.kernels import packed_graph
from pathmeet.operators import index as index_ops
from pathmeet.operators import meet
from pathmeet.operators.graph import build_graph
from pathmeet.operators.index import build_index
from pathmeet.plans import workloads as w
from pathmeet.scratch import staged
from pathmeet.sources import synth, tables


def test_kernel_measures_equal_the_engine(spark, sf):
    g = w.graph_of(spark, sf, "g_social_2_8")
    sample = staged(w.sample_nodes(g, size=25), "sample")
    pairs = staged(w.sample_pairs(sample), "pairs")
    row = experiment(spark, packed_graph(g), [(4.0, 0), (16.0, 0)], 25, timed=3).orderBy("alpha").collect()
    for got, alpha in zip(row, (4.0, 16.0)):
        ix = build_index(g, alpha, sources=sample)
        answers = meet.distance(ix, pairs).collect()
        open_ = [r for r in answers if r.case not in ("source_anchor", "target_anchor")]
        probes = [r.probes + 4 for r in answers if r.case in ("meet", "unanswered")]
        assert (got.n, got.m, got.anchors, got.pairs, got.wrong) == (g.n, g.m, ix.anchors.count(), 300, 0)
        assert got.meeting == sum(r.dist is not None for r in open_) and got.worst_lookups == max(probes, default=None)
        assert got.mean_radius == pytest.approx(ix.radius.agg(F.avg("r")).first()[0])
        assert got.query_ms is None or got.query_ms > 0


def test_coverage_rises_with_alpha(spark, sf):
    graph = packed_graph(w.graph_of(spark, sf, "g_social_4_16"))
    found = [measured(graph, alpha, 0, 20, 7, 0) for alpha in (1.0, 4.0, 16.0)]
    share = [x["meeting"] / max(1, x["open_pairs"]) for x in found]
    assert share == sorted(share) and [x["anchors"] for x in found] == sorted((x["anchors"] for x in found), reverse=True)
    assert all(x["wrong"] == 0 for x in found)


def test_an_interrupted_save_leaves_the_index_before(spark, tmp_path, monkeypatch):
    folder = f"file://{tmp_path}/index"
    one, two = (build_index(build_graph(synth.grid(spark, n, 5))) for n in (4, 6))
    index_ops.save_index(one, folder)

    def die(*_):
        raise KeyboardInterrupt

    monkeypatch.setattr(index_ops, "replace_file", die)
    with pytest.raises(KeyboardInterrupt):
        index_ops.save_index(two, folder)
    monkeypatch.undo()
    assert index_ops.load_index(spark, folder).radius.count() == 20
    opened = index_ops.load_index(spark, folder)
    index_ops.save_index(two, folder)
    assert index_ops.load_index(spark, folder).radius.count() == 30 and opened.vicinity.count() > 0  # readers of the one before go on


def test_large_ids_give_query_numbers(spark):
    ids = spark.createDataFrame([(2**52 + i,) for i in range(4)], "id long")
    pairs = w.sample_pairs(ids).collect()
    assert len({r.qid for r in pairs}) == len(pairs) == 6


def test_knn_edges_by_blocks_equal_brute_force(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(50, 6))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = {(r.src // 16, r.dst // 16) for r in tables.knn_edges(rows, k=3, block=7).collect()}
    v = np.floor(np.abs(x * 1000) + 0.5) * np.sign(x)
    d = ((v[:, None] - v[None, :]) ** 2).sum(2)
    assert got == {(i, j) for i in range(50) for j in sorted(set(range(50)) - {i}, key=lambda j: (d[i, j], j))[:3]}


def test_a_cluster_without_a_shared_folder_is_refused(spark, monkeypatch):
    class Holder:
        def isDefined(self):
            return False

    class Stub:
        master = "spark://host:7077"
        _jsc = type("J", (), {"sc": lambda self: type("S", (), {"getCheckpointDir": lambda self: Holder()})()})()

    session = type("Session", (), {"conf": type("C", (), {"get": lambda self, *_: None})(), "sparkContext": Stub()})()
    with pytest.raises(RuntimeError, match="checkpoint"):
        scratch.shared_dir(session)
