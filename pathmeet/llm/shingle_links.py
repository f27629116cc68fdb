"""Near duplicates by word shingles: all links of Jaccard similarity ``least`` or more, checked exactly.

The near-duplicate stage of the pipeline: SimHash fingerprints of five-word shingles are linked by
vantage-point shards (``simhash_links``), and every group that they form is a candidate. A
radius wide enough for similarity 0.8 (some 17 of 64 bits) prunes no vantage-point shard,
since unrelated fingerprints lie about 32 bits apart, so further candidates come from
min-hash bands. Two sets of similarity s share one of ``bands`` bands of ``rows`` minima with
probability ``1 - (1 - s ** rows) ** bands``: 0.99993 at s = 0.8. A link counts only after
the similarity of the whole sets has been computed.

Documents of one shingle set are one node. Buckets with the same members are searched once,
and a bucket returns a forest that connects what its links connect, never all pairs. A
bucket of more than ``most`` members is dealt to blocks: each block is searched with the
bucket's least member, and then only those pairs of blocks that still hold different components.

Defined results: texts without words are one node without shingles; a text with fewer
words than a shingle is one shingle; the component is the smallest id (nulls last) that
links reach. Repeated rows stay repeated, and rows with one id are told apart by number. A, B,
..., Z are read as lower case. Very long texts are read whole. Empty tables give empty results.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pathmeet.components import component_labels
from pathmeet.joins import bounded_join, hot_join
from pathmeet.llm.simhash_links import all_but_first, forest, near_duplicates
from pathmeet.rows import numbered, without_rows
from pathmeet.scratch import discard, settled, staged

#: Shingles whose minima are taken at once.
BLOCK = 1 << 12
#: Odd constant of the rolling combination of word hashes.
ODD = 0x9E3779B97F4A7C15


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit (constants of the usual finalizers)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_set(text: bytes, words: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles of a text."""
    from xxhash import xxh64_intdigest

    parts = text.lower().split()  # as in simhash_links
    if not parts:
        return np.zeros(0, np.uint64)
    hashes = np.fromiter(map(xxh64_intdigest, parts), np.uint64, len(parts))
    width = min(words, len(parts))
    out = np.zeros(len(parts) - width + 1, np.uint64)
    for k in range(width):
        out = out * np.uint64(ODD) + hashes[k : k + len(out)]
    return np.unique(mixed(out))


def minima(shingles: np.ndarray, bands: int, rows: int) -> list[int]:
    """One 64-bit value per band, of ``rows`` minima each; none of an empty set."""
    if not len(shingles):
        return []
    salts = mixed(np.arange(1, bands * rows + 1, dtype=np.uint64) * np.uint64(ODD)) | np.uint64(1)
    least = np.full(bands * rows, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), BLOCK):
        some = shingles[at : at + BLOCK]
        for i, salt in enumerate(salts):
            product = some * salt
            least[i] = min(least[i], (product ^ (product >> np.uint64(32))).min())
    held = np.zeros(bands, np.uint64)
    for column in least.reshape(bands, rows).T:
        held = mixed(held * np.uint64(ODD) + column)
    return held.view(np.int64).tolist()


def sketched(text: Column, words: int, bands: int, rows: int) -> Column:
    """(key, bands): the digest of the shingle set and its bands."""
    kind = T.StructType([T.StructField("key", T.StringType()), T.StructField("bands", T.ArrayType(T.LongType()))])

    @F.arrow_udf(kind)
    def sketch(texts: pa.Array) -> pa.Array:
        from xxhash import xxh3_128_hexdigest

        keys, held = [], []
        for x in texts.to_pylist():
            shingles = shingle_set(x or b"", words)
            keys.append(xxh3_128_hexdigest(shingles.tobytes()))
            held.append(minima(shingles, bands, rows))
        return pa.StructArray.from_arrays([pa.array(keys, pa.string()), pa.array(held, pa.list_(pa.int64()))], names=["key", "bands"])

    return sketch(text.cast("binary"))


def with_sets(text: Column, words: int) -> Column:
    """(key, shingles): the digest of the shingle set and the set as bytes."""
    kind = T.StructType([T.StructField("key", T.StringType()), T.StructField("shingles", T.BinaryType())])

    @F.arrow_udf(kind)
    def read(texts: pa.Array) -> pa.Array:
        from xxhash import xxh3_128_hexdigest

        held = [shingle_set(x or b"", words).tobytes() for x in texts.to_pylist()]
        return pa.StructArray.from_arrays([pa.array(map(xxh3_128_hexdigest, held), pa.string()), pa.array(held, pa.binary())], names=["key", "shingles"])

    return read(text.cast("binary"))


def bucket_forest(sets: list[np.ndarray], least: float) -> np.ndarray:
    """Least index of the component of each set under the links of similarity ``least`` or more.

    Every pair outside the component of the first sets is compared, so no link between components is missed."""
    n = len(sets)
    sizes = np.array([len(x) for x in sets])
    codes = np.unique(np.concatenate(sets), return_inverse=True)[1]
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    seen = np.zeros(codes.max() + 1, np.int64)

    def alike(i: int) -> np.ndarray:
        own = codes[starts[i] : starts[i] + sizes[i]]
        seen[own] = 1
        shared = np.add.reduceat(seen[codes], starts)
        seen[own] = 0
        return np.flatnonzero(shared >= least * (sizes + sizes[i] - shared) - 1e-9)

    near = alike(0)
    label = forest(n, np.zeros(len(near), np.int64), near)
    for i in np.flatnonzero(label != 0):
        near = alike(i)
        if (label[near] != label[i]).any():
            ties = np.flatnonzero(label != np.arange(n))
            label = forest(n, np.concatenate([ties, np.full(len(near), i)]), np.concatenate([label[ties], near]))
    return label


def searched(members: DataFrame, group: list[str], sets: DataFrame, least: float) -> DataFrame:
    """Links (src, dst) between keys that share a group. ``members``: group and key; ``sets``: (key, shingles)."""

    def search(table: pa.Table) -> pa.Table:
        keys = table.column("key").to_pylist()
        label = bucket_forest([np.frombuffer(x, np.uint64) for x in table.column("shingles").to_pylist()], least)
        apart = np.flatnonzero(label != np.arange(len(keys)))
        return pa.table({"src": pa.array([keys[i] for i in apart], pa.string()), "dst": pa.array([keys[i] for i in label[apart]], pa.string())})

    return members.join(sets, "key").select(*group, "key", "shingles").groupBy(*group).applyInArrow(search, "src string, dst string")


def similar_links(nodes: DataFrame, sets: DataFrame, least: float, most: int = 512) -> DataFrame:
    """Links (src, dst) that connect what similar keys of one bucket connect.

    ``nodes`` (written): (band, value, key, n, first), with the number of keys and the least key of the bucket."""
    block = F.pmod(F.xxhash64("key"), F.ceil(F.col("n") / most))
    dealt = nodes.withColumn("blocks", F.ceil(F.col("n") / most)).withColumn("block", block)
    guests = dealt.where("key = first and blocks > 1").withColumn("other", F.explode(F.expr("sequence(0L, blocks - 1)"))).where("other <> block")
    alone = dealt.select("band", "value", "block", "key").unionByName(guests.select("band", "value", F.col("other").alias("block"), "key"))
    links = staged(searched(alone, ["band", "value", "block"], sets, least), "shingle-links")
    large = dealt.where("blocks > 1")
    if large.isEmpty():
        return links
    labels = component_labels(links).withColumnRenamed("id", "key")
    named = large.join(labels, "key", "left").withColumn("comp", F.coalesce("comp", "key"))
    pairs = named.withColumn("other", F.explode(F.expr("sequence(0L, blocks - 1)"))).where("other <> block")
    pairs = pairs.select("band", "value", F.least("block", "other").alias("a"), F.greatest("block", "other").alias("b"), "key", "comp")
    group = ["band", "value", "a", "b"]
    open_ = staged(pairs.groupBy(*group).agg(F.min("comp").alias("x"), F.max("comp").alias("y")).where("x <> y").select(*group), "shingle-open")
    members = bounded_join(pairs, open_, group, "left_semi").select(*group, "key")
    return links.unionByName(searched(members, group, sets, least))


def similar_documents(
    spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, least: float = 0.8, bands: int = 24, rows: int = 5,
    radius: int = 2, row_col: str | None = None, most: int = 512,
) -> DataFrame:
    """One row per document: id, row, component_id, root (the digest that names the component)."""
    if row_col is None:
        docs, row_col = numbered(docs, "shingle-docs")
    slim = docs.select(F.col(id_col).alias("id"), F.col(row_col).alias("row"), F.col(text_col).alias("text"))
    read = staged(slim.select("id", "row", sketched(F.col("text"), words, bands, rows).alias("s")).select("id", "row", "s.key", "s.bands"), "shingle-sketches")
    distinct = staged(read.groupBy("key").agg(F.min("id").alias("least"), F.min("row").alias("row"), F.any_value("bands").alias("bands"), F.count("*").alias("size")), "shingle-distinct")
    linked = settled("shingle-prints", lambda: near_duplicates(spark, slim, "id", "text", words=words, radius=radius, row_col="row").select("row", "root"))
    by_print = read.select("row", "key").join(linked, "row").select("key", F.lit(-1).alias("band"), F.col("root").alias("value")).distinct()
    # texts without words are one node already, and have no bands
    banded = distinct.select("key", F.posexplode("bands").alias("band", "value")).unionByName(by_print)
    banded = staged(banded, "shingle-banded")
    members = [F.bit_xor(F.xxhash64("key")).alias("x"), F.bit_xor(F.xxhash64(F.lit(1), "key")).alias("y"), F.min("key").alias("first"), F.count("*").alias("n")]
    shared = banded.groupBy("band", "value").agg(*members).where("n > 1")
    buckets = staged(shared.groupBy("x", "y", "first", "n").agg(F.min(F.struct("band", "value")).alias("b")).select("b.band", "b.value", "n", "first"), "shingle-buckets")
    nodes = staged(bounded_join(banded, buckets, ["band", "value"]), "shingle-members")
    wanted = staged(bounded_join(distinct.select("key", "row"), nodes.select("key").distinct(), "key", "left_semi").select("row"), "shingle-wanted")
    # one document of each set is read again
    texts = bounded_join(slim.select("row", "text"), wanted, "row", "left_semi")
    sets = staged(texts.select(with_sets(F.col("text"), words).alias("s")).select("s.key", "s.shingles"), "shingle-sets")
    links = settled("shingle-all-links", lambda: similar_links(nodes, sets, least, most))
    for done in (linked, banded, buckets, nodes, wanted, sets):
        discard(done)
    labelled = component_labels(links).withColumnRenamed("id", "key").join(distinct.select("key", "least"), "key")
    groups = labelled.groupBy("comp").agg(F.min("least").alias("component"))
    home = labelled.select("key", "comp").join(groups, "comp").select("key", F.col("comp").alias("root"), "component")
    known = distinct.select("key", "least", "size").join(home, "key", "left").where("size > 1 or root is not null")
    single = staged(known.select("key", "size", F.coalesce("root", "key").alias("root"), F.when(F.col("root").isNull(), F.col("least")).otherwise(F.col("component")).alias("component"), F.lit(True).alias("known")), "shingle-components")
    out = hot_join(read.select("id", "row", "key"), single, ["key"], "size", read.count())
    return out.select(F.col("id").alias(id_col), "row", F.when(F.col("known"), F.col("component")).otherwise(F.col("id")).alias("component_id"), F.coalesce("root", "key").alias("root"))


def keep_dissimilar(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The document with the smallest id of each component, with all its columns."""
    held, row = numbered(docs, "near-docs")
    groups = lambda: similar_documents(spark, held, id_col, text_col, row_col=row, **options).select(F.col(id_col).alias("id"), "row", "root")
    found = settled("near-found", groups)
    return without_rows(held, settled("near-gone", lambda: all_but_first(found, "root", "id").withColumnRenamed("row", row)), row)
