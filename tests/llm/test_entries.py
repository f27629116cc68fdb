"""Registered queries without SQL, over their whole tables, against brute force."""

from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
import zlib
from pyspark.sql import functions as F

from pathmeet import llm
from pathmeet.llm import packing, shingle_links
from tests_llm_brute import brute_components, brute_print, similar_components


def test_op4_entry(spark, sf):
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").orderBy("doc_id").collect()
    prints = [brute_print(r.text) for r in rows]
    roots = brute_components(prints, 2)
    expected = {(r.doc_id, f"{p:016x}", rows[root].doc_id) for r, p, root in zip(rows, prints, roots)}
    got = llm.queries()["op4_simhash_links"](spark, sf).collect()
    assert len(got) == len(rows) and {(r.doc_id, r.fingerprint, r.component_id) for r in got} == expected


def test_op7_entry(spark, sf):
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(packing.default_vocabulary())
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    ids = {r.doc_id: np.array([*model.encode(r.text or "", add_special_tokens=False).ids, 1], "<u4") for r in rows}
    got = llm.queries()["op7_packing"](spark, sf).collect()
    parts, fill = defaultdict(list), defaultdict(list)
    for r in got:
        assert r.doc_tokens == len(ids[r.doc_id]) and r.ids_crc32 == zlib.crc32(ids[r.doc_id][r.start : r.start + r.length].tobytes())
        parts[r.doc_id].append((r.start, r.length))
        fill[r.sequence_id].append((r.offset, r.length))
    for held, whole in ((parts, {d: len(x) for d, x in ids.items()}), (fill, None)):
        for key, pieces in held.items():
            at = 0
            for start, length in sorted(pieces):
                assert start == at
                at += length
            assert at == whole[key] if whole else at == 2048 or key == max(fill)
    assert set(parts) == set(ids)


def test_near_duplicate_stage_equals_all_pairs(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").orderBy("doc_id").collect()]
    expected = similar_components(rows)
    got = {r.doc_id: r.component_id for r in shingle_links.similar_documents(spark, docs).collect()}
    assert got == expected
    kept = shingle_links.keep_dissimilar(spark, docs).collect()
    assert Counter(r.doc_id for r in kept) == Counter(set(expected.values()))


@pytest.mark.parametrize("name", ["op1_exact_dedup", "op2_warc_bundles", "op3_source_mixing", "op8_sharding", "op10_vector_search"])
def test_entries_with_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    cursor = con.execute(llm.oracle_sql()[name])
    names = [d[0] for d in cursor.description]
    expected = Counter(tuple(r) for r in cursor.fetchall())
    got = llm.queries()[name](spark, sf)
    assert sorted(got.columns) == sorted(names)
    assert Counter(tuple(r) for r in got.select(*names).collect()) == expected


@pytest.mark.parametrize("name", ["op5_pair_quality", "op9_toxicity"])
def test_scores_do_not_depend_on_the_split_of_rows(spark, sf, name):
    """Scores are a function of the text alone: brute force is the model on each text by itself."""
    module = __import__(f"pathmeet.llm.{'pair_quality' if name[2] == '5' else 'toxicity'}", fromlist=["scored"])
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    one = {r.doc_id: r.score for r in llm.queries()[name](spark, sf).collect()}
    other = {r.doc_id: r.score for r in module.scored(spark, docs.repartition(7, F.col("doc_id")), labels).collect()}
    assert one.keys() == other.keys() and all(abs(one[k] - other[k]) < 1e-9 for k in one)
