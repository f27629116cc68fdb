"""SimHash fingerprints of word shingles and all links within a Hamming radius.

Distinct fingerprints are partitioned by vantage-point trees fitted on samples: a node
sends a fingerprint left if it is within the median distance of its vantage point. Each
fingerprint is at home in one shard and visits every shard that the triangle inequality
allows to hold one within the radius, so every link is found in a home shard. Shards are
counted after routing, and those that came out too large get a tree of their own, round
by round; where a tree no longer divides a shard, its home rows are dealt to tasks. Inside a
shard two more vantage points order the members, and only bins whose distances differ by
at most the radius are compared. A shard returns a spanning forest of its links, never all
pairs; components follow from the forests.

Defined results: null, empty and blank texts have fingerprint zero; a text with fewer
words than a shingle is one shingle; very long texts are read whole, in blocks; copies share
a fingerprint and so one component; the component is the smallest id (nulls last) that
links reach. Repeated rows stay repeated, and rows with one id are told apart by number. Empty
tables give empty results. Other columns are kept, whatever their names.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pathmeet.components import component_labels
from pathmeet.joins import hot_join
from pathmeet.rows import numbered, without_rows
from pathmeet.scratch import settled, staged

#: Shingles whose bits are summed at once.
BLOCK = 1 << 15


def fingerprint(text: bytes, words: int = 3, seed: int = 42) -> int:
    """Bit i is set where it is set in over half of the XXH64 values of all shingles."""
    from xxhash import xxh64_intdigest

    parts = text.lower().split()  # bytes.lower changes A-Z only; bytes.split knows [\x20\x09-\x0D] only
    if not parts:
        return 0
    joined = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    if len(parts) > words:
        starts, ends = starts[: 1 - words], ends[words - 1 :]
    else:
        starts, ends = starts[:1], ends[-1:]
    counts = np.zeros(64, np.int64)
    n = len(starts)
    for at in range(0, n, BLOCK):
        some = [xxh64_intdigest(joined[a:b], seed) for a, b in zip(starts[at : at + BLOCK].tolist(), ends[at : at + BLOCK].tolist(), strict=True)]
        bits = np.unpackbits(np.array(some, "<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        counts += bits.sum(axis=0, dtype=np.int64)
    return int(np.packbits(counts * 2 > n, bitorder="little").view("<u8")[0])


def fingerprints(text, words: int = 3, seed: int = 42):
    """Fingerprint column (long) of a text column."""

    @F.arrow_udf(T.LongType())
    def of(texts: pa.Array) -> pa.Array:
        values = [fingerprint(x or b"", words, seed) for x in texts.to_pylist()]
        return pa.array(np.array(values, np.uint64).view(np.int64), pa.int64())

    return of(text.cast("binary"))


def distances(some: np.ndarray, one) -> np.ndarray:
    return np.bitwise_count(some ^ np.uint64(one))


def fit_tree(sample: np.ndarray, depth: int) -> list[tuple[int, int]]:
    """Vantage point and median of each inner node of a complete tree, children of i at 2i+1 and 2i+2.

    The vantage point of a node is the one of a few candidates with the widest spread of distances."""
    nodes: list[tuple[int, int]] = [(0, 0)] * ((1 << depth) - 1)
    held = {0: sample}
    for i in range(len(nodes)):
        own = held.pop(i, sample[:0])
        base = own if len(own) else sample if len(sample) else np.zeros(1, np.uint64)
        best = max(base[:: max(1, len(base) // 16)][:16], key=lambda v: float(distances(base, v).std()))
        d = distances(base, best)
        middle = int(np.median(d))
        nodes[i] = (int(best), middle)
        if len(own):
            near = distances(own, best) <= middle
            held[2 * i + 1], held[2 * i + 2] = own[near], own[~near]
    return nodes


def route(points: np.ndarray, home: np.ndarray, nodes: list[tuple[int, int]], radius: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(leaf, indexes, at home) of the points in every leaf that they must reach."""
    stack = [(0, np.arange(len(points)), home)]
    while stack:
        node, who, own = stack.pop()
        if not len(who):
            continue
        if node >= len(nodes):
            yield node - len(nodes), who, own
            continue
        vantage, middle = nodes[node]
        d = distances(points[who], vantage).astype(np.int16)
        left, right = d <= middle + radius, d > middle - radius
        stack.append((2 * node + 1, who[left], (own & (d <= middle))[left]))
        stack.append((2 * node + 2, who[right], (own & (d > middle))[right]))


def forest(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least index of the component of each of ``n`` nodes under the links a-b."""
    label = np.arange(n)
    while len(a):
        low, high = np.minimum(label[a], label[b]), np.maximum(label[a], label[b])
        if not (low < high).any():
            break
        np.minimum.at(label, high, low)
        while (label[label] != label).any():
            label = label[label]
    return label


def shard_forest(points: np.ndarray, home: np.ndarray, radius: int, most_pairs: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Links (member, root) that connect the members of a shard that links within ``radius`` connect."""
    n = len(points)
    first = points[np.argmax(home)]
    one = distances(points, first).astype(np.int64)
    second = points[np.argmin(np.abs(one - 32))]
    two = distances(points, second).astype(np.int64)
    order = np.lexsort((two, one))
    points, home, key = points[order], home[order], (one * 128 + two)[order]
    edges, held = (np.zeros(0, np.int64), np.zeros(0, np.int64)), 0
    found: list[tuple[np.ndarray, np.ndarray]] = []
    where = np.flatnonzero(home)
    cuts = np.flatnonzero(np.diff(key[where], prepend=-1))
    for begin, end in zip(cuts, np.append(cuts[1:], len(where)), strict=True):
        own = where[begin:end]
        d1, d2 = divmod(int(key[own[0]]), 128)
        ranges = [np.searchsorted(key, [k * 128 + max(0, d2 - radius), k * 128 + d2 + radius + 1]) for k in range(max(0, d1 - radius), d1 + radius + 1)]
        near = np.concatenate([np.arange(lo, hi) for lo, hi in ranges])
        step = max(1, (1 << 22) // max(1, len(near)))
        for at in range(0, len(own), step):
            some = own[at : at + step]
            i, j = np.nonzero(np.bitwise_count(points[some][:, None] ^ points[near][None, :]) <= radius)
            a, b = some[i], near[j]
            other = a != b
            found.append((a[other], b[other]))
            held += int(other.sum())
            if held > most_pairs:
                label = forest(n, *(np.concatenate([edges[k], *(x[k] for x in found)]) for k in (0, 1)))
                apart = np.flatnonzero(label != np.arange(n))
                edges, found, held = (apart, label[apart]), [], 0
    label = forest(n, *(np.concatenate([edges[k], *(x[k] for x in found)]) for k in (0, 1)))
    apart = np.flatnonzero(label != np.arange(n))
    return points[apart], points[label[apart]]


#: Rows of a shard, visits included, for each of its home rows, beyond which it is split once more.
VISITS = 8
SHARDS = "shard long, fp long, home boolean"


def shards(prints: DataFrame, radius: int, leaf: int, sample: int) -> DataFrame:
    """(shard, fp, home): the fingerprints in every shard that they must reach, shards of about ``leaf`` home rows."""
    rows = prints.count()
    open_ = prints.select(F.lit(0).cast("long").alias("shard"), "fp", F.lit(True).alias("home"))
    large, done, free = {0: (rows, rows)} if rows > leaf else {}, [], 1  # rows and home rows of shards to split
    while large:
        total = sum(n for n, _ in large.values())
        wanted = min(sample, 32 * (total // leaf + 1) + 4096)  # grows with the leaves
        some = open_.where(F.pmod(F.xxhash64("fp", F.lit(free)), F.lit(1 << 30)) < int((1 << 30) * min(1.0, wanted / total)))
        drawn: dict[int, list[int]] = {}
        for r in some.select("shard", "fp").collect():
            drawn.setdefault(r.shard, []).append(r.fp)
        trees = {}
        for shard, (n, own) in sorted(large.items()):
            depth = min(12, max(1, math.ceil(math.log2(max(own / leaf, n / (VISITS * leaf))))))
            trees[shard] = free, fit_tree(np.array(sorted(drawn.get(shard, [])), np.int64).view(np.uint64), depth)
            free += 1 << depth
        routed = staged(_routed(open_, trees, radius), "simhash-routed")
        sizes = {r.shard: (r.n, r.own) for r in routed.groupBy("shard").agg(F.count("*").alias("n"), F.count_if("home").alias("own")).collect()}
        parent = {base + i: shard for shard, (base, nodes) in trees.items() for i in range(len(nodes) + 1)}
        over = {shard: n for shard, n in sizes.items() if n[1] > 4 * leaf or n[0] > 4 * VISITS * leaf}
        stuck = {shard: n for shard, (n, _) in over.items() if n > 0.8 * large[parent[shard]][0]}
        large = {shard: n for shard, n in over.items() if shard not in stuck}
        settled = routed.where(~F.col("shard").isin(*over)) if over else routed
        done.append(settled)
        if stuck:
            tight, free = _dealt(routed.where(F.col("shard").isin(*stuck)), stuck, leaf, free)
            done.append(tight)
        open_ = routed.where(F.col("shard").isin(*large)) if large else None
    out = done[0] if done else open_
    for more in done[1:]:
        out = out.unionByName(more)
    return out


def _routed(rows: DataFrame, trees: dict, radius: int) -> DataFrame:
    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            shard = batch.column(0).to_numpy(zero_copy_only=False)
            points = batch.column(1).to_numpy(zero_copy_only=False).view(np.uint64)
            home = batch.column(2).to_numpy(zero_copy_only=False)
            for one in np.unique(shard).tolist():
                inside = np.flatnonzero(shard == one)
                base, nodes = trees[one]
                for leaf, who, own in route(points[inside], home[inside], nodes, radius):
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.full(len(who), base + leaf, np.int64)), pa.array(points[inside][who].view(np.int64)), pa.array(own)], names=["shard", "fp", "home"]
                    )

    return rows.mapInArrow(send, SHARDS)


def _dealt(rows: DataFrame, stuck: dict[int, int], leaf: int, free: int) -> tuple[DataFrame, int]:
    """Shards that no tree divides: home rows are dealt to parts, and every part sees all members."""
    listed = []
    for shard, n in sorted(stuck.items()):
        parts = -(-n // leaf)
        listed.append((shard, free, parts))
        free += parts
    deal = F.broadcast(rows.sparkSession.createDataFrame(listed, "shard long, base long, parts long"))
    dealt = rows.join(deal, "shard").withColumn("part", F.explode(F.expr("sequence(0L, parts - 1)")))
    own = F.col("home") & (F.pmod(F.xxhash64("fp"), F.col("parts")) == F.col("part"))
    return dealt.select((F.col("base") + F.col("part")).alias("shard"), "fp", own.alias("home")), free


def hamming_links(spark: SparkSession, prints: DataFrame, radius: int = 2, sample: int = 1 << 18, leaf: int | None = None) -> DataFrame:
    """Links (src, dst) between distinct fingerprints ``fp``; they connect exactly what links within ``radius`` connect.

    ``sample`` bounds the fingerprints that trees are fitted on; all of them are indexed and searched."""
    leaf = leaf or max(4096, int(16 * math.sqrt(prints.count())))

    def search(table: pa.Table) -> pa.Table:
        points = table.column("fp").to_numpy().view(np.uint64)
        home = table.column("home").to_numpy()
        a, b = shard_forest(points, home, radius) if home.any() else (points[:0], points[:0])
        return pa.table({"src": pa.array(a.view(np.int64)), "dst": pa.array(b.view(np.int64))})

    return shards(prints, radius, leaf, sample).groupBy("shard").applyInArrow(search, "src long, dst long")


def near_duplicates(
    spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, radius: int = 2, seed: int = 42, row_col: str | None = None
) -> DataFrame:
    """One row per document: id, row, fp (long), fingerprint (hex), component_id, root (a fingerprint that names the component)."""
    row = F.monotonically_increasing_id() if row_col is None else F.col(row_col)
    printed = staged(docs.select(F.col(id_col).alias("id"), row.alias("row"), fingerprints(F.col(text_col), words, seed).alias("fp")), "simhash-prints")
    distinct = staged(printed.groupBy("fp").agg(F.min("id").alias("least"), F.count("*").alias("size")), "simhash-distinct")
    links = staged(hamming_links(spark, distinct, radius), "simhash-links")
    labels = component_labels(links)
    linked = labels.withColumnRenamed("id", "fp").join(distinct, "fp")
    least = linked.groupBy("comp").agg(F.min("least").alias("component"))
    groups = linked.select("fp", "comp").join(least, "comp").select("fp", F.col("comp").alias("root"), "component")
    # prints that neither repeat nor have a link are their own component and need no join
    known = distinct.join(groups, "fp", "left").where("size > 1 or root is not null")
    home = staged(known.select("fp", "size", F.coalesce("root", "fp").alias("root"), F.when(F.col("root").isNull(), F.col("least")).otherwise(F.col("component")).alias("component"), F.lit(True).alias("known")), "simhash-components")
    out = hot_join(printed, home, ["fp"], "size", printed.count())
    return out.select(
        F.col("id").alias(id_col), "row", "fp", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"),
        F.when(F.col("known"), F.col("component")).otherwise(F.col("id")).alias("component_id"), F.coalesce("root", "fp").alias("root"),
    )


def all_but_first(found: DataFrame, group: str, id_col: str) -> DataFrame:
    """(row) of every row of ``found`` (written; id, row, group) but the one of its group with the smallest id (nulls last), then number."""
    order = F.struct(F.col(id_col).isNull().alias("z"), F.col(id_col).alias("i"), F.col("row").alias("r"))
    first = staged(found.groupBy(group).agg(F.count("*").alias("size"), F.min(order).alias("first")).where("size > 1"), "groups-first")
    return hot_join(found.select(group, "row"), first, [group], "size", found.count()).where("first.r <> row").select("row")


def keep_one(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The document with the smallest id of each component of linked fingerprints, with all its columns."""
    held, row = numbered(docs, "simhash-docs")
    groups = lambda: near_duplicates(spark, held, id_col, text_col, row_col=row, **options).select(F.col(id_col).alias("id"), "row", "root")
    found = settled("simhash-found", groups)
    return without_rows(held, settled("simhash-gone", lambda: all_but_first(found, "root", "id").withColumnRenamed("row", row)), row)


def op4_simhash_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return near_duplicates(spark, docs).select("doc_id", "fingerprint", "component_id")


QUERIES = {"op4_simhash_links": op4_simhash_links}
SQL: dict[str, str] = {}
