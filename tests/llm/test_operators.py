"""Each operator against brute force, and on nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns."""

import base64
import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from pathmeet.llm import exact_dedup, language_id, packing, pair_quality, sharding, simhash_links, source_mixing, toxicity, vector_search, warc_bundles
from pathmeet.llm.labelled import held_out
from pathmeet.llm.text_kernels import word_counts

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, h string, size string, fp string, part string, rid string, at string"
ODD = [
    (1, "The same words here and there.", "en", "a"),
    (2, "The same  words\there and there.\n", "en", "b"),
    (3, None, "en", None),
    (4, "", None, "a"),
    (5, " \n\t ", "fr", None),
    (6, "word " * 30_000, "en", "a"),
    (7, "The same words here and there.", "en", "a"),
    (7, "The same words here and there.", "en", "a"),
    (8, "Ünïcode é 漢字   text <|endoftext|>", "de", "c"),
    (9, "one", None, "c"),
    (None, "one", "en", "z"),
    (10, "les mots de la langue sont ici pour être lus et relus", "fr", "b"),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(*r, len(r[1] or ""), "x", "x", "x", "x", "x", "x") for r in ODD], SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def squeezed(text):
    return re.sub(r"[\x20\x09-\x0D]", "", text or "")


def split(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


# --- exact dedup ----------------------------------------------------------------------------


def brute_dedup(rows):
    groups = defaultdict(list)
    for doc, text in rows:
        groups[squeezed(text)].append((-len(text or ""), doc is None, doc or 0, doc))
    return {k: (min(v)[3], len(v)) for k, v in groups.items()}


@pytest.mark.parametrize("capacity", [1, 3, 1000])
def test_exact_dedup(spark, odd, none, capacity):
    got = exact_dedup.exact_duplicates(spark, odd, capacity=capacity).collect()
    expected = brute_dedup([(r[0], r[1]) for r in ODD])
    by_sha = {hashlib.sha256(k.encode()).hexdigest(): v for k, v in expected.items()}
    assert len(got) == len(ODD)
    for r in got:
        assert (r.keep_id, r.group_size) == by_sha[r.text_sha256]
    assert sum(r.kept for r in got) == len(expected)  # wholly repeated rows are kept once
    assert exact_dedup.exact_duplicates(spark, none).count() == 0
    kept = exact_dedup.keep_first(spark, odd)
    assert kept.columns == odd.columns and sorted(squeezed(r.text) for r in kept.collect()) == sorted(expected)


def test_exact_dedup_chains_collisions(spark, odd):
    weak = exact_dedup.exact_duplicates(spark, odd, capacity=2, key=F.length("norm").cast("long")).collect()
    strong = exact_dedup.exact_duplicates(spark, odd).collect()
    view = lambda rows: Counter((r.doc_id, r.keep_id, r.group_size, r.kept, r.text_sha256) for r in rows)
    assert view(weak) == view(strong)


def test_directory_doubles_until_no_bucket_is_overfull(spark):
    near = spark.range(3000).select(F.shiftleft("id", 44).alias("h"))  # one narrow range of hashes: its bucket splits again and again
    postings = near.unionByName(spark.range(1000).select(F.xxhash64("id").alias("h"))).unionByName(spark.range(500).select(F.lit(1 << 44).alias("h")))
    found = exact_dedup.directory(postings, 700, 2).collect()
    depth = {r.local_depth for r in found}
    assert len(depth) > 3 and min(depth) == 2 and max(depth) >= 10 and sum(r.held for r in found) == 4500
    assert all(r.held <= 700 for r in found)
    held = exact_dedup.routed(postings, exact_dedup.directory(postings, 700, 2)).groupBy("bucket").count().collect()
    assert {r.bucket: r["count"] for r in held} == {r.start: r.held for r in found}
    same = exact_dedup.directory(spark.range(50).select(F.lit(9).cast("long").alias("h")), 10).collect()
    assert [(r.local_depth, r.held) for r in same] == [(0, 50)]  # equal hashes keep an overflow chain


def test_owner_tasks_read_the_index_in_place(spark, odd):
    from pathmeet.scratch import bucketed

    index = bucketed(spark.range(100).select("id", F.pmod("id", F.lit(7)).alias("bucket")).repartition(4, "bucket"), "t", "bucket", 4)
    plan = index.groupBy("bucket", "id").count()._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan


def test_stages_keep_rows_apart_whatever_ids_and_columns_are_called(spark):
    names = ["_id", "_n", "_gone", "_m", "_size", "_taken", "_copy", "row", "row_number", "mix", "place", "bucket", "component_id"]
    texts = ["one two three four five six", "ONE two three four five six", "one  two three four five six", "quite other words stand here now", None]
    rows = [(i, t, "en", "s", *[100 + k + 10 * j for k in range(len(names))]) for j, (i, t) in enumerate(zip([5, 5, 5, None, None], texts))]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, " + ", ".join(f"{n} long" for n in names))
    view = lambda df: Counter(tuple(r) for r in df.collect())
    first = exact_dedup.keep_first(spark, docs)
    assert first.columns == docs.columns and view(first) == Counter(r for r in rows if r[1] != texts[0])  # the longest original stays
    mixed = source_mixing.mixed_documents(spark, docs)
    assert mixed.columns == docs.columns and view(mixed) == Counter(rows)  # one source, share 100 %: every row once
    known = language_id.keep_identified(spark, docs, support=1)
    assert known.columns == docs.columns and view(known) - Counter(rows) == Counter()
    one = simhash_links.keep_one(spark, docs)
    assert one.columns == docs.columns and {r.text for r in one.collect()} >= {texts[3], None}
    two = spark.createDataFrame([(5, "alpha beta gamma delta"), (5, "one two three four"), (3, "one two three four")], "doc_id long, text string")
    assert Counter(r.text for r in simhash_links.keep_one(spark, two).collect()) == Counter(["alpha beta gamma delta", "one two three four"])


# --- WARC -----------------------------------------------------------------------------------


def test_warc_round_trip(spark, tmp_path):
    pages = [(i, f"http://h{i % 3}/\nx", ["<p>same</p>", None, "", "<p>é " + "x" * (i * 50_000), f"<b>{i}</b>"][i % 5], "k") for i in range(30)]
    table = spark.createDataFrame(pages, "page_id long, url string, html string, _key string").repartition(3)
    manifest = warc_bundles.write_bundles(spark, table, folder=f"file://{tmp_path}/w", frame_bytes=20_000, bundle_bytes=200_000)
    got = {int(r.record_id): r for r in warc_bundles.read_bundles(spark, manifest, with_payload=True, frames_per_task=2).collect()}
    assert len(got) == 30
    first = {}
    for i, _, html, _ in pages:
        first.setdefault((html or "").encode(), i)
    for i, _, html, _ in pages:
        raw, r = (html or "").encode(), got[i]
        assert (r.payload_bytes, r.payload_digest) == (len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode())
        assert (r.record_type, r.refers_to) == (("response", None) if first[raw] == i else ("revisit", str(first[raw])))
        assert bytes(r.payload) == (raw if first[raw] == i else b"")
    for m in manifest.collect()[::4]:  # seekable: one record by one frame
        head, block = warc_bundles.read_record(m.bundle, m.frame, m.offset)
        assert head["WARC-Record-ID"] == f"<urn:x-record:{m.record_id}>"
        assert head["WARC-Date"] and head["Content-Type"] == "application/http;msgtype=response"
        assert head["WARC-Type"] == "revisit" or block == (pages[int(m.record_id)][2] or "").encode()
    empty = spark.createDataFrame([], "page_id long, url string, html string")
    assert warc_bundles.read_bundles(spark, warc_bundles.write_bundles(spark, empty)).count() == 0
    short = warc_bundles.write_bundles(spark, table, least_bytes=10_000)
    assert warc_bundles.read_bundles(spark, short).where("record_type = 'revisit'").count() == 0
    found = warc_bundles.read_bundles(spark, manifest, frames_per_task=1)
    assert found.rdd.getNumPartitions() > 8  # file names are not merged into one task
    assert warc_bundles.verified(found).count() == 30
    with pytest.raises(ValueError, match="revisit"):
        warc_bundles.verified(found.withColumn("payload_bytes", F.col("payload_bytes") + (F.col("record_type") == "revisit").cast("int")))
    nameless = spark.createDataFrame([(None, "http://a", "same", "k")] * 3, table.schema)
    assert [r.record_type for r in warc_bundles.read_bundles(spark, warc_bundles.write_bundles(spark, nameless)).collect()] == ["response"] * 3


# --- mixing ---------------------------------------------------------------------------------


def level_by_rounds(caps, weights, budget):
    """Reshares what is over the caps by weight until nothing is."""
    target, open_, left = {}, set(caps), budget
    while open_:
        total = sum(weights[s] for s in open_)
        over = {s for s in open_ if weights[s] * left > caps[s] * total}
        if not over:
            return target | {s: weights[s] * left / total for s in open_}
        for s in over:
            target[s] = caps[s]
        left, open_ = left - sum(caps[s] for s in over), open_ - over
    return target


def test_mixing(spark, odd, none):
    got = source_mixing.allotments(spark, odd).collect()
    assert len(got) == len(ODD) and sorted(r.size for r in got) == sorted(len(split(r[1])) for r in ODD)
    sizes = Counter()
    for r in ODD:
        sizes[r[3]] += len(split(r[1]))
    names = sorted(sizes, key=lambda s: (s is None, s))
    weights = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    expected = level_by_rounds({s: 3 * sizes[s] for s in names}, weights, sum(sizes.values()))
    taken = Counter()
    for r in got:
        assert r.target == pytest.approx(expected[r.source]) and r.source_size == sizes[r.source] and 0 <= r.taken <= 3 * r.size
        taken[r.source] += r.taken
    assert sum(taken.values()) == sum(sizes.values()) and all(abs(expected[s] - taken[s]) <= 1 for s in names)  # packets of one word
    assert {(r.doc_id, r.start, r.taken) for r in got} == {(r.doc_id, r.start, r.taken) for r in source_mixing.allotments(spark, odd.repartition(5)).collect()}
    assert source_mixing.allotments(spark, none).count() == 0
    mix = source_mixing.mixed_documents(spark, odd)
    assert mix.columns == odd.columns
    assert sum(len(split(r.text)) for r in mix.collect()) == sum(taken.values())
    queue = source_mixing.queued(odd, "doc_id", "text", "source", (5, 2, 1), 3, 1.0, "mix", None)
    order = sorted((r.tick, r.sid, r.words) for r in source_mixing.packets(queue, 7, 3).collect())
    for budget in (1, 5, 100, 29_000, sum(w for *_, w in order)):  # the cut of the sequence, found by sorting it whole
        total, at = 0, 0
        while total + order[at][2] < budget:
            total, at = total + order[at][2], at + 1
        assert source_mixing.cut_of(source_mixing.packets(queue, 7, 3), budget) == (*order[at][:2], budget - total)


def test_word_counts_on_slices():
    import pyarrow as pa

    texts = ["a b  c", None, "", "  \n", "x", "y z ", "\x0bq\x1c", "é b"] * 3
    expected = [len(split(t)) for t in texts]
    assert word_counts(pa.array(texts)).tolist() == expected and word_counts(pa.array(texts)[3:11]).tolist() == expected[3:11]


# --- SimHash --------------------------------------------------------------------------------


def brute_print(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    values = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(v >> b & 1 for v in values) > len(values))


def brute_components(points, radius):
    label = list(range(len(points)))

    def find(i):
        while label[i] != i:
            i = label[i]
        return i

    for i in range(len(points)):
        for j in range(i):
            if (points[i] ^ points[j]).bit_count() <= radius:
                a, b = find(i), find(j)
                label[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(points))]


def test_simhash(spark, odd, none):
    got = simhash_links.near_duplicates(spark, odd).collect()
    assert Counter((r.doc_id, r.fingerprint) for r in got) == Counter((r[0], f"{brute_print(r[1]):016x}") for r in ODD)
    rows = sorted((r[0] is None, r[0] or 0, brute_print(r[1])) for r in ODD)
    roots = brute_components([r[2] for r in rows], 2)
    expected = {(None if missing else doc, rows[root][1]) for (missing, doc, _), root in zip(rows, roots)}
    assert {(r.doc_id, r.component_id) for r in got} == expected
    assert simhash_links.near_duplicates(spark, none).count() == 0
    kept = simhash_links.keep_one(spark, odd)
    assert kept.columns == odd.columns and kept.count() == len(set(roots))


def test_vantage_point_shards_lose_no_link(spark):
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 63, 300, dtype=np.uint64)
    near = base[rng.integers(0, 300, 900)] ^ (np.uint64(1) << rng.integers(0, 64, 900, dtype=np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 900, dtype=np.uint64))
    dense = np.uint64(12345) ^ (np.uint64(1) << rng.integers(0, 64, 400, dtype=np.uint64))
    points = np.unique(np.concatenate([base, near, dense]))
    prints = spark.createDataFrame([(int(p),) for p in points.view(np.int64)], "fp long")
    links = simhash_links.hamming_links(spark, prints, leaf=64).collect()
    place = {p: i for i, p in enumerate(points.view(np.int64).tolist())}
    label = simhash_links.forest(len(points), np.array([place[r.src] for r in links]), np.array([place[r.dst] for r in links]))
    expected = brute_components(points.tolist(), 2)
    assert [int(x) for x in label] == expected
    assert len(links) < 20 * len(points)  # forests, not all pairs
    sizes = [r["count"] for r in simhash_links.shards(prints, 2, 16, 1 << 18).groupBy("shard").count().collect()]
    assert max(sizes) < 0.9 * len(points) and len(sizes) > 8  # shards that come out too large are split again or dealt
    links = simhash_links.hamming_links(spark, prints, leaf=16).collect()
    label = simhash_links.forest(len(points), np.array([place[r.src] for r in links]), np.array([place[r.dst] for r in links]))
    assert [int(x) for x in label] == expected


# --- classifiers ----------------------------------------------------------------------------


def test_held_out_rule(spark):
    rows = spark.range(200).select("id", held_out(F.col("id")).alias("out")).collect()
    assert all(r.out == (zlib.crc32(str(r.id).encode()) % 4 == 2) for r in rows)


@pytest.mark.parametrize("module, label, threshold, least, size", [(pair_quality, "quality", 0.7, 0.95, "sf0.01"), (toxicity, "toxic", 0.3, 0.9, "sf0.01")])
def test_classifiers_on_held_out_rows(spark, odd, none, module, label, threshold, least, size):
    folder = f"/root/testdata/{size}"
    docs, labels = spark.read.parquet(f"{folder}/documents.parquet"), spark.read.parquet(f"{folder}/labels.parquet")
    got = module.scored(spark, docs, labels)
    assert got.count() == docs.count() and got.where("score < 0 or score > 1 or score is null").isEmpty()
    assert got.where(f"predicted <> cast(score >= {threshold} as int)").isEmpty()
    judged = got.where("held_out").join(labels, "doc_id")
    assert judged.agg(F.avg((F.col("predicted") == F.col(label)).cast("double"))).first()[0] >= least
    hidden = labels.where(~held_out(F.col("doc_id"))).unionByName(labels.where(held_out(F.col("doc_id"))).withColumn(label, 1 - F.col(label)))
    again = {r.doc_id: r.score for r in module.scored(spark, docs, hidden).collect()}
    assert all(r.score == again[r.doc_id] for r in got.collect())  # held-out labels are not read
    few = spark.createDataFrame([(1, 1, 0), (1, 1, 0), (None, 0, 1), (10, None, None)], "doc_id long, quality int, toxic int")
    assert module.scored(spark, odd, few).count() == len(ODD)
    assert module.scored(spark, none, few.limit(0)).count() == 0


def test_long_and_null_texts_train(spark):
    from pathmeet.llm.labelled import training_sample

    ids = [i for i in range(40) if zlib.crc32(str(i).encode()) % 4 != 2][:3]
    docs = spark.createDataFrame([(ids[0], "x" * 50_000 + "END"), (ids[1], None), (ids[2], "short")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, k % 2) for k, i in enumerate(ids)], "doc_id long, toxic int")
    found = training_sample(docs, labels, "toxic", 10, 1000)
    assert sorted((len(t), y) for t, y in found) == [(0, 1), (5, 0), (1003, 0)] and max(found)[0].endswith("END")


def test_dictionaries_are_trained_on_their_own_class():
    rng = np.random.default_rng(7)
    syllables = ["ba", "do", "fi", "gu", "ke", "lo", "mi", "nu", "po", "ra", "se", "ti", "vo", "wu", "xi", "za"]
    word = lambda: "".join(rng.choice(syllables, rng.integers(2, 5)))
    texts = [([word() for _ in range(80)], k % 4 == 0) for k in range(600)]
    for words, bad in texts:
        for at in rng.integers(0, 80, 5 * bad):
            words[at] = ["wretch", "knavery", "villain"][at % 3]
    rows = [(" ".join(words), int(bad)) for words, bad in texts]
    model = toxicity.train(rows[:450])
    for bad in (b"wretch", b"knavery", b"villain"):  # a dictionary may hold a word without its first letter, so its effect is asked for
        assert bad not in model.ordinary
        assert all(saved[0] > 0 for saved in model.distances([b"bado", bad, b"gukelo"]))
    right = (model.score([t for t, _ in rows[450:]]) >= 0.3) == np.array([y for _, y in rows[450:]], bool)
    assert right.mean() > 0.95
    swapped = toxicity.train([(t, 0) for t, _ in rows[:450]])  # deleting a class deletes the score
    assert set(swapped.score(["villain", None])) == {0.0}


def test_language_fusion(spark, odd, none):
    texts = {"en": "the words of this text are read here and there again", "fr": "les mots de ce texte sont lus ici et encore une fois"}
    pages = [(i, f"http://{'www.' * (i % 2)}h{i % 4}.example.{'fr' if i % 2 else 'com'}/p", f'<html lang="{lang}"><body><p>{texts[lang]} {i}</p><script>var x = "no";</script></body></html>', "x") for i, lang in enumerate(["en", "fr"] * 20)]
    pages += [(100, None, None, "x"), (101, "http://h1.example.fr/z", "<html><p>12 34</p></html>", "x"), (102, "bad", "<p>les mots sont lus ici encore</p>", "x"), (102, "bad", "<p>les mots sont lus ici encore</p>", "x")]
    table = spark.createDataFrame(pages, "page_id long, url string, html string, lang string")
    found = language_id.pages_languages(spark, table).collect()
    assert len(found) == len(pages)
    lang = {r.id: r.lang for r in found}
    assert all(lang[i] == ("fr" if i % 2 else "en") for i in range(40))
    assert lang[100] is None and lang[101] is None and lang[102] == "fr"
    # a page without readable text follows its declared language and host
    mute = table.unionByName(spark.createDataFrame([(200, "http://h1.example.fr/q", '<html lang="FR"></html>', "x")], table.schema))
    assert {r.id: r.lang for r in language_id.pages_languages(spark, mute).collect()}[200] == "fr"
    assert language_id.pages_languages(spark, table.limit(0)).count() == 0
    kept = language_id.keep_identified(spark, odd)
    assert kept.columns == odd.columns and language_id.keep_identified(spark, none).count() == 0
    assert {1, 6, 7, 10} <= {r.doc_id for r in kept.collect()} and 4 not in {r.doc_id for r in kept.collect()}


def test_seventy_languages_and_long_pages_are_learned(spark):
    rng = np.random.default_rng(2)
    names = [f"{a}{b}" for a in "abcdefghij" for b in "klmnopq"]
    texts = {lang: ["".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz"), 6)) for _ in range(12)] for lang in names}
    rows = [(i, f"http://h{i}.org/", f'<html lang="{lang}">' + " ".join(rng.choice(texts[lang], 40)) + "</html>") for i, lang in enumerate(names * 4)]
    long = [(1000 + i, "http://x.org/", '<html lang="zz">' + "zuzu zozo zizi " * 4000 + "</html>") for i in range(4)]  # a language of long pages only
    unnamed = [(2000 + i, None, " ".join(rng.choice(texts[lang], 40))) for i, lang in enumerate(names)] + [(3000, None, "zozo zizi zuzu")]
    pages = spark.createDataFrame(rows + long + unnamed, "page_id long, url string, html string")
    lang = {r.id: r.lang for r in language_id.pages_languages(spark, pages).collect()}
    assert all(lang[i] == x for i, x in enumerate(names * 4)) and all(lang[2000 + i] == x for i, x in enumerate(names))
    assert lang[1000] == "zz" and lang[3000] == "zz"
    assert all(x is None for x in {r.id: r.lang for r in language_id.pages_languages(spark, pages, support=5).collect()}.values())


def test_trigram_counts_do_not_depend_on_blocks():
    text = "les mots " * 300_000
    assert abs(language_id.trigram_counts(text) - np.bincount(language_id.trigrams(text.encode()), minlength=language_id.BUCKETS)).sum() <= 12
    assert language_id.trigram_counts(None).sum() == 0


# --- packing --------------------------------------------------------------------------------


def test_packing_equals_the_tokenizer(spark, odd, none):
    from tokenizers import Tokenizer

    path = packing.default_vocabulary()
    model = Tokenizer.from_file(path)
    placed = packing.with_offsets(packing.tokenised(odd.repartition(3), path))
    packed = packing.windows(placed, window=64, most_open=1)
    got = packing.pieces(packed).collect()
    ids = defaultdict(list)
    for doc, text, *_ in ODD:
        ids[doc].append([*model.encode(text or "", add_special_tokens=False).ids, 1])
    covered = defaultdict(int)
    for r in got:
        raw = np.array(ids[r.doc_id][0], "<u4")
        assert r.doc_tokens == len(raw) and r.ids_crc32 == zlib.crc32(raw[r.start : r.start + r.length].tobytes()) and r.offset + r.length <= 64
        covered[r.doc_id] += r.length
    assert all(covered[d] == sum(map(len, x)) for d, x in ids.items())
    fill = defaultdict(list)
    for r in got:
        fill[r.sequence_id].append((r.offset, r.length))
    last = max(fill)
    for s, parts in fill.items():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at == 64 or s == last
    whole = packing.sequences(packed).orderBy("sequence_id").collect()
    assert [r.sequence_id for r in whole] == list(range(last + 1)) and all(len(r.ids) == 64 or (len(r.ids) & (len(r.ids) - 1)) == 0 for r in whole)
    stream = [x for r in whole for x in r.ids[: r.tokens]]
    assert Counter(stream) == Counter(x for lists in ids.values() for one in lists for x in one)
    for r in got[:50]:
        assert whole[r.sequence_id].ids[r.offset : r.offset + r.length] == ids[r.doc_id][0][r.start : r.start + r.length]
    assert packing.packed_pieces(none, path).count() == 0


def test_fast_model_equals_tokenizers_on_odd_texts():
    from tokenizers import Tokenizer

    path = packing.default_vocabulary()
    model, encode = Tokenizer.from_file(path), packing.encoder(path)
    runs = [" " * 1_500_000 + "x", "\n" * 1_200_000 + " x", "x" + "\t " * 600_000, "a" * 300_000, " a" * 100_000, "a <|endoftext|> b", " " * 9000 + "<|endoftext|>"]
    for text in [*runs, "a  b", "  a\n b \n", "x\n\n  y  ", "it's they'll <|endoftext|>", " ", "", "\t \t a", " é  è́ 1 23 $%^ _", "a \x1c b \x85 c\xa0 d", "a" * 5000, " " * 5000, " " * 4095 + "a", "a" + "\u2003" * 5000 + "b"]:
        assert np.frombuffer(encode(text), "<u4").tolist() == model.encode(text, add_special_tokens=False).ids


# --- sharding -------------------------------------------------------------------------------


def test_sharding_round_trip_versions_and_tiers(spark, odd, none):
    store = sharding.Store(spark, fanout=2, least_bytes=1000, target_bytes=40_000, most=4)
    many = odd.unionByName(odd).unionByName(odd).repartition(4)
    assert store.append(none) == 1 and store.read(odd.schema).count() == 0
    for _ in range(3):
        store.append(many, arrival_bytes=3000)
    before, small = store.version(), store.manifest().count()
    version = store.compact_fully()
    assert version > before and store.manifest().count() < small
    back = store.read(odd.schema).select(*odd.columns)
    count = lambda df: Counter(tuple(r) for r in df.collect())
    one = count(many)
    assert count(back) == Counter({k: 3 * v for k, v in one.items()})
    assert not store.compact()  # no tier is full any more
    with pytest.raises(FileExistsError):
        store.commit(store.manifest(), version - 1)  # another writer was first
    assert store.versions() == [version - 1, version]  # the version before is still there
    assert count(store.read(odd.schema, version - 1).select(*odd.columns)) == count(back)
    store.vacuum(keep=1)
    assert store.versions() == [version] and count(store.read(odd.schema).select(*odd.columns)) == count(back)


def test_a_writer_that_dies_leaves_the_store_readable(spark, odd, monkeypatch):
    store = sharding.Store(spark)
    store.append(odd)

    def die(draft, final):
        raise KeyboardInterrupt

    monkeypatch.setattr(store, "_publish", die)  # dies between writing the version and giving it its name
    with pytest.raises(KeyboardInterrupt):
        store.append(odd)
    monkeypatch.undo()
    assert store.version() == 1 and store.read(odd.schema).count() == len(ODD)
    assert store.append(odd) == 2 and store.read(odd.schema).count() == 2 * len(ODD)


def test_arrivals_of_different_columns_merge(spark):
    store = sharding.Store(spark, fanout=2)
    for i in range(4):
        store.append(spark.createDataFrame([(i, "t", "x")], ["doc_id", "text", ["a", "_shard"][i % 2]]).coalesce(1))
    store.compact_fully()
    back = store.read(spark.createDataFrame([], "doc_id long, text string, a string, _shard string").schema)
    assert sorted((r.doc_id, r.a, r["_shard"]) for r in back.collect()) == [(0, "x", None), (1, None, "x"), (2, "x", None), (3, None, "x")]
    assert "_shard_" in back.columns


# --- vector search --------------------------------------------------------------------------


def test_vector_search(spark):
    rng = np.random.default_rng(3)
    rows = [(i, [float(x) for x in rng.normal(0, 0.2, 8).astype(np.float32)], "x") for i in range(0, 400)]
    rows += [(1000 + i, rows[i % 3][1], "x") for i in range(20)]  # ties
    rows += [(500, None, "x"), (550, [None] * 8, "x"), (600, [float("nan")] * 8, "x"), (650, [float("inf")] * 8, "x"), (700, [0.5] * 3, "x"), (None, rows[0][1], "x"), (750, [], "x"), (50, rows[50][1], "x")]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>, score string").repartition(3)
    usable = {i: np.floor(256 * np.array(v)).astype(np.int64) for i, v, _ in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)}
    expected = set()
    for q, v in usable.items():
        if q % 50 == 0:
            held = [(-int(v @ c), i) for i, c in usable.items() if i != q and len(c) == len(v)]
            expected |= {(q, k + 1, i, -s) for k, (s, i) in enumerate(sorted(held)[:5])}
    for options in ({}, {"block": 3, "sample": 7, "batch": 16, "held_rows": 30}):
        got = vector_search.top_k(spark, table, **options)
        assert {(r.query_id, r["rank"], r.vec_id, r.score) for r in got.collect()} == expected
    assert vector_search.top_k(spark, table.limit(0)).count() == 0


def test_segment_bounds_hold():
    rng = np.random.default_rng(1)
    a, b = rng.normal(size=(50, 24)), rng.normal(size=(60, 24))
    tight = None
    for segments in (1, 2, 4, 8, 24):
        bound = vector_search.statistics(a, segments) @ vector_search.statistics(b, segments).T
        assert (bound >= a @ b.T - 1e-9).all()
        tight = bound.mean() if tight is None else min(tight, bound.mean())
    assert tight <= (vector_search.statistics(a, 1) @ vector_search.statistics(b, 1).T).mean()


def test_any_finite_component_takes_part(spark):
    big = [1e6, 1.0], [2.0**19, -3.0], [1e300, 2.0], [-1e300, 5.0], [0.5, 0.25], [3e15, -3e15], [1e308, 1e308]
    rows = [(50 * i, list(v)) for i, v in enumerate(big)] + [(50 * i + 1, [v[0], v[1] + 1]) for i, v in enumerate(big)]
    rows += [(1000 + i, [float(x)] * n) for i, x in enumerate(np.linspace(-1, 1, 40)) for n in [1 + i % 13]]  # many lengths
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    exact = {i: [int(np.floor(256 * x)) if abs(x) < 1e15 else int(x) * 256 for x in v] for i, v in rows}
    expected = set()
    for q, v in exact.items():
        if q % 50 == 0:
            held = sorted((-sum(a * b for a, b in zip(v, c)), i) for i, c in exact.items() if i != q and len(c) == len(v))
            expected |= {(q, n + 1, i, min(2**63 - 1, max(-(2**63), -s))) for n, (s, i) in enumerate(held[:5])}
    for options in ({}, {"sample": 3, "block": 2}):
        got = {(r.query_id, r["rank"], r.vec_id, r.score) for r in vector_search.top_k(spark, table, **options).collect()}
        assert got == expected


def test_levels_prune_the_given_vectors():
    import pyarrow.parquet as pq

    table = pq.read_table("/root/testdata/sf0.1/embeddings.parquet")
    (ids, v), = vector_search._matrices(table.combine_chunks().to_batches()[0].select(["vec_id", "embedding"]), 256)
    mine = ids % 50 == 0
    search = vector_search.Search(ids[mine], v[mine], 5)
    search.add(ids[:1000], v[:1000])
    search.reduce()
    search.shares[:] = 0
    search.add(ids[1000:], v[1000:])
    shares = search.shares / (mine.sum() * (len(ids) - 1000))
    assert shares[0] == 1 and (np.diff(shares) <= 0).all() and shares[-1] < 0.2  # few pairs are scored exactly
