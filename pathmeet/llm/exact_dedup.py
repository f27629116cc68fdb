"""Exact duplicate removal through an extendible-hash index on shared files.

Every document gives an entry ``(hash, digest, place)``; entries of one hash and digest are
combined into a few postings per text, so a text with very many copies stays small. The
directory of hash prefixes starts at a depth that the row count suggests and is doubled
while a bucket holds more than ``capacity`` postings of different hashes; only overfull
buckets are split and counted again. Postings are written to shared files by bucket, which
is a range of hashes. Owner tasks read their buckets in place, chain the postings of one
hash, and decide size and survivor of every class; the texts of all repeated hashes are
then compared byte by byte. Built-in functions only.

Defined results: null text counts as empty, and empty texts equal each other; of equal
texts the one with most code points in its original text stays, then the smallest id
(null ids last), then one arbitrary row of wholly repeated rows. Very long texts are hashed
and compared whole. Empty tables give empty results. Columns other than the id and the text
are kept as they are, whatever their names.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathmeet.joins import bounded_join, hot_join
from pathmeet.rows import numbered, without_rows
from pathmeet.scratch import bucketed, discard, settled, staged

#: The white space that normalisation deletes, [\x20\x09-\x0D].
WHITE = " \t\n\x0b\x0c\r"


def normalised(text: Column) -> Column:
    return F.translate(F.coalesce(text, F.lit("")), WHITE, "")


#: Postings that the copies of one text are spread over, and the postings that an owner task reads.
SALTS, OWNER_ROWS = 16, 1 << 20


def slot(h: Column, depth: int) -> Column:
    """The first ``depth`` bits of a 64-bit hash as a number."""
    return F.shiftrightunsigned(h, 64 - depth) if depth else F.lit(0).cast("long")


def directory(postings: DataFrame, capacity: int, depth: int = 0) -> DataFrame:
    """Buckets ``(local_depth, slot, held, start)`` after all splits; ``start`` is a bucket's first hash.

    A round doubles the directory: it gives one more bit to the buckets that hold more than
    ``capacity`` postings and counts their halves; the others keep their local depth. A bucket whose
    postings all have one hash cannot be split and keeps an overflow chain."""
    held = [F.count("*").alias("held"), F.min("h").alias("least"), F.max("h").alias("most")]
    level = staged(postings.groupBy(slot(F.col("h"), depth).alias("slot")).agg(*held), "dedup-level")
    done = []
    while True:
        overfull = (F.col("held") > capacity) & (F.col("least") != F.col("most")) & F.lit(depth < 64)
        done.append(level.where(~overfull).select(F.lit(depth).alias("local_depth"), "slot", "held", (F.shiftleft("slot", 64 - depth) if depth else F.col("slot")).alias("start")))
        split = level.where(overfull).select(F.col("slot").alias("full"))
        if split.isEmpty():
            break
        inside = bounded_join(postings.withColumn("full", slot(F.col("h"), depth)), split, "full", "left_semi")
        depth += 1
        level = staged(inside.groupBy(slot(F.col("h"), depth).alias("slot")).agg(*held), "dedup-level")
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    return staged(out, "dedup-directory")


def routed(rows: DataFrame, buckets: DataFrame) -> DataFrame:
    """Adds ``bucket`` (its first hash) and ``local_depth`` by looking up the prefixes of ``h`` in the directory."""
    depths = [r.local_depth for r in buckets.select("local_depth").distinct().orderBy("local_depth").collect()] or [0]  # 65 at most
    tries = F.explode(F.array(*(F.struct(F.lit(d).alias("local_depth"), slot(F.col("h"), d).alias("slot")) for d in depths)))
    looked_up = rows.withColumn("at", tries).select(*rows.columns, "at.local_depth", "at.slot")
    pointers = buckets.select("local_depth", "slot", F.col("start").alias("bucket"))
    return bounded_join(looked_up, pointers, ["local_depth", "slot"]).drop("slot")


def exact_duplicates(
    spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = 100_000,
    key: Column | None = None, depth: int | None = None, row_col: str | None = None,
) -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256, row, bucket, local_depth, chain.

    ``key`` replaces the 64-bit hash of the normalised text ``norm`` (tests force collisions), ``depth`` the
    first depth of the directory; ``row_col`` names a column that numbers the rows, if there is one."""
    row = F.monotonically_increasing_id() if row_col is None else F.col(row_col)
    base = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("raw"), row.alias("row"))
    base = base.withColumn("norm", normalised(F.col("raw"))).withColumn("h", F.xxhash64("norm") if key is None else key)
    entries = staged(base.select("id", "h", F.sha2("norm", 256).alias("sha"), F.length("raw").alias("chars"), "row"), "dedup-entries")
    rows = entries.count()

    order = F.struct((-F.col("chars")).alias("c"), F.col("id").isNull().alias("z"), F.col("id").alias("i"), F.col("row").alias("r"))
    combined = entries.groupBy("h", "sha", F.pmod("row", F.lit(SALTS)).alias("salt")).agg(F.count("*").alias("copies"), F.min(order).alias("best"))
    postings = staged(combined.drop("salt"), "dedup-postings")
    total = postings.count()
    first = math.ceil(math.log2(max(1, total / capacity))) if depth is None else depth
    buckets = directory(postings, capacity, first)
    owners = max(int(spark.conf.get("spark.sql.shuffle.partitions", "200")), math.ceil(total / OWNER_ROWS))
    index = bucketed(routed(postings, buckets).repartition(owners, "bucket"), "dedup-index", "bucket", owners)

    # owner tasks: the files are bucketed, so neither step moves a posting
    classes = index.groupBy("bucket", "local_depth", "h", "sha").agg(F.sum("copies").alias("size"), F.min("best").alias("best"))
    one_hash = Window.partitionBy("bucket", "h")
    chained = classes.withColumn("chain", F.row_number().over(one_hash.orderBy("sha")) - 1).withColumn("length", F.count("*").over(one_hash))
    owned = staged(chained, "dedup-classes")
    discard(postings)
    _compare_bytes(base, owned.where((F.col("size") > 1) | (F.col("length") > 1)).select("bucket", "h").distinct())

    out = hot_join(entries, owned, ["h", "sha"], "size", rows)
    return out.select(
        F.col("id").alias(id_col),
        F.col("best.i").alias("keep_id"),
        F.col("size").alias("group_size"),
        (F.col("best.r") == F.col("row")).alias("kept"),
        F.col("sha").alias("text_sha256"),
        "row",
        "bucket",
        "local_depth",
        "chain",
    )


def _compare_bytes(base: DataFrame, repeated: DataFrame) -> None:
    """Compares the bytes of all texts whose hash repeats, bucket by bucket.

    Each class of one hash and digest must hold one byte string. Copies combine before
    the shuffle, so a text with very many copies moves once per task."""
    repeated = staged(repeated, "dedup-repeated")
    texts = bounded_join(base.select("h", "norm"), repeated, "h").groupBy("bucket", "h", "norm").agg(F.count("*").alias("n"))
    clash = texts.groupBy("bucket", "h", F.sha2("norm", 256).alias("sha")).agg(F.count("*").alias("strings")).where("strings > 1")
    if not clash.isEmpty():
        raise ValueError("different texts share both hash and digest")


def keep_first(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns; rows are told apart by numbers, so repeated ids do no harm."""
    held, row = numbered(docs, "dedup-docs")
    lost = lambda: exact_duplicates(spark, held, id_col, text_col, row_col=row, **options).where(~F.col("kept")).select(F.col("row").alias(row))
    return without_rows(held, settled("dedup-gone", lost), row)


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return exact_duplicates(spark, docs).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


OP1_SQL = r"""
WITH n AS (
  SELECT doc_id, length(coalesce(text, '')) AS chars,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS text_sha256
  FROM documents)
SELECT doc_id, first_value(doc_id) OVER w AS keep_id,
       count(*) OVER (PARTITION BY text_sha256) AS group_size,
       doc_id = first_value(doc_id) OVER w AS kept, text_sha256
FROM n WINDOW w AS (PARTITION BY text_sha256 ORDER BY chars DESC, doc_id)
"""

QUERIES = {"op1_exact_dedup": op1_exact_dedup}
SQL = {"op1_exact_dedup": OP1_SQL}
