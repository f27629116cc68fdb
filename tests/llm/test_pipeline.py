"""The corpus pipeline against a plain rendering of its stages, and its contract."""

from collections import Counter

import pytest

from pathmeet.llm import exact_dedup, shingle_links

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def test_stages_keep_columns_and_take_effect(spark, sf):
    assert [name for name, _ in corpus_pipeline.STAGES] == ["language_id", "exact_dedup", "simhash_near_dedup", "source_mixing", "packing"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    now, sizes = docs, [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = corpus_pipeline.staged(stage(spark, now, sf), name)
        assert out.columns == docs.columns
        if name == "exact_dedup":
            kept = {r.doc_id for r in exact_dedup.exact_duplicates(spark, now).collect() if r.kept}
            assert Counter(r.doc_id for r in out.select("doc_id").collect()) == Counter(kept)
        if name == "simhash_near_dedup":
            assert {r.doc_id for r in out.collect()} == {r.component_id for r in shingle_links.similar_documents(spark, now).collect()}
        now = out
        sizes.append(now.count())
    assert sizes[1] >= 0.98 * sizes[0]  # clean documents stay
    pieces = corpus_pipeline.STAGES[-1][1](spark, now, sf).collect()
    assert {p.doc_id for p in pieces} == {r.doc_id for r in now.select("doc_id").collect()}
    total = sum(p.length for p in pieces)
    assert max(p.sequence_id for p in pieces) == (total - 1) // 2048


def test_run_returns_the_pieces(spark, sf):
    out = corpus_pipeline.run(spark, sf)
    assert {"doc_id", "sequence_id", "offset", "length"} <= set(out.columns) and out.count() > 0
