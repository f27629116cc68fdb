"""Near duplicates by shingle sets against all pairs, and their place in the pipeline."""

import random

import corpus_pipeline
import pytest

from pathmeet.llm import shingle_links


def shingles(text):
    words = (text or "").split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def brute_components(rows):
    sets = [shingles(text) for _, text in rows]
    label = {doc: doc for doc, _ in rows}

    def find(i):
        while label[i] != i:
            i = label[i]
        return i

    for i, (a, _) in enumerate(rows):
        for j, (b, _) in enumerate(rows[:i]):
            both = sets[i] | sets[j]
            if not both or len(sets[i] & sets[j]) >= 0.8 * len(both):
                x, y = find(a), find(b)
                label[max(x, y)] = min(x, y)
    return {doc: find(doc) for doc, _ in rows}


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(3)
    found = [(1, None), (2, ""), (3, "one two"), (4, "one  two"), (5, "one two three")]
    for _ in range(60):
        words = [f"w{rng.randrange(3000)}" for _ in range(rng.choice([40, 100, 300]))]
        for changes in (0, 1, 2, 3, 6):
            other = list(words)
            for at in rng.sample(range(len(words)), changes):
                other[at] = f"x{rng.randrange(10**6)}"
            found.append((len(found) + 1, " ".join(other)))
    return found


def test_similar_documents_equal_all_pairs(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in shingle_links.similar_documents(spark, docs).collect()}
    assert got == brute_components(rows)


def test_large_buckets_are_dealt_to_blocks(spark):
    rng = random.Random(8)
    words = [f"w{i}" for i in range(200)]
    rows = [(i, " ".join([*words[:190], *(f"x{rng.randrange(10**6)}" for _ in range(rng.choice([4, 10, 24])))])) for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in shingle_links.similar_documents(spark, docs, most=4).collect()}
    assert got == brute_components(rows)


def test_rows_without_and_with_repeated_ids(spark):
    same = " ".join(f"w{i}" for i in range(50))
    docs = spark.createDataFrame([(None, same), (7, same + " end"), (7, "other words altogether here now"), (8, same), (None, "last one")], "doc_id long, text string")
    assert shingle_links.similar_documents(spark, docs.limit(0)).count() == 0
    got = sorted((r.doc_id or 0, r.component_id or 0) for r in shingle_links.similar_documents(spark, docs).collect())
    assert got == [(0, 0), (0, 7), (7, 7), (7, 7), (8, 7)]


def test_large_bucket_joins_components_that_the_first_set_misses():
    import numpy as np

    chain = [np.arange(i * 10, i * 10 + 100, dtype=np.uint64) for i in range(6)]  # neighbours share 90 of 110
    assert shingle_links.bucket_forest(chain, 0.8).tolist() == [0] * 6
    assert shingle_links.bucket_forest([chain[0], chain[4], chain[5]], 0.8).tolist() == [0, 1, 1]


def test_pipeline_drops_documents_with_a_changed_word(spark, sf):
    rng = random.Random(4)
    words = [f"w{rng.randrange(3000)}" for _ in range(100)]
    texts = [" ".join(words), " ".join([*words[:50], "changed", *words[51:]]), " ".join(f"y{rng.randrange(3000)}" for _ in range(100))]
    docs = spark.createDataFrame([(i, t, "en", "a", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES:
        if name.endswith("near_dedup"):
            docs = corpus_pipeline.staged(stage(spark, docs, sf), name)
    assert sorted(r.doc_id for r in docs.collect()) == [0, 2]
