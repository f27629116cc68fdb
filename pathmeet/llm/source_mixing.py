"""Mixing sources to target weights by weighted fair queueing.

Documents of a source are shuffled (by the md5 of id and seed) and queue up ``max_epochs``
times. They are sent in packets of at most ``budget / PACKETS`` words, so that one very long
document cannot hold up its source; a packet that ends at word ``w`` of its source's queue
finishes at virtual time ``w / weight``, kept as a whole number of ticks. Packets are sorted
by (finish, source) over all sources and the sequence is cut where the word budget is spent:
the packet at the cut is taken in part, nothing behind it is taken. A source whose queue
ends early leaves its share to the others, so taken words come to the water level that
``targets`` states, within one packet.

The sort is by ranges of virtual time. Sources are served at constant rates, so ranges of
equal width hold about equally many words; their totals tell which range the cut is in, and
only that range is divided further and, when small, sorted. The running word counts inside
a source are prefix sums over hash-prefix buckets, then inside each bucket, so a source with
most of all rows is spread over many tasks.

Defined results: null text has no words; sources go by code point, null last; a source
without words has target 0; rows that repeat an id are separate documents; null ids shuffle
like the text "null" but stay apart from it; very long texts are counted whole. Ties in the
shuffle go by id and size. Empty tables give empty results. The table of sources is sorted in
one task, which suits some 10^7 sources.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathmeet.joins import bounded_join
from pathmeet.llm.text_kernels import leading_words, word_count
from pathmeet.rows import free_name, numbered
from pathmeet.scratch import settled, staged

#: Rows that a bucket of the running sums is meant to hold, and the most bits of a bucket number.
BUCKET_ROWS, BUCKET_BITS = 256, 16
#: The budget divided by the words of a packet, the ranges that virtual time is divided into, and the packets that one task sorts.
PACKETS, RANGES, LEAF = 1 << 20, 4096, 50_000


def targets(sizes: DataFrame, weights: tuple[int, ...] = (5, 2, 1), max_epochs: int = 3, share: float = 1.0) -> DataFrame:
    """(source, source_size) to (source, sid, weight, source_size, target).

    Water level: sources in the order of cap / weight fill up while their cap is below
    what the rest of the budget gives them; the others share what is left by weight."""
    named = Window.orderBy(F.col("source").asc_nulls_last())
    filled = Window.orderBy(F.col("cap") / F.col("weight"), "sid")
    before = filled.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.col("sid") % len(weights) + 1).cast("int"))
    t = sizes.withColumn("sid", (F.row_number().over(named) - 1).cast("long")).withColumn("weight", weight.cast("long"))
    t = t.withColumn("cap", F.col("source_size") * max_epochs)
    t = t.withColumn("budget", F.floor(F.sum("source_size").over(everything) * F.lit(share)).cast("long")).withColumn("all_weight", F.sum("weight").over(everything))
    t = t.withColumn("spent", F.coalesce(F.sum("cap").over(before), F.lit(0))).withColumn("gone", F.coalesce(F.sum("weight").over(before), F.lit(0)))
    t = t.withColumn("full", F.col("cap") * (F.col("all_weight") - F.col("gone")) <= F.col("weight") * (F.col("budget") - F.col("spent")))
    t = t.withColumn("left", F.col("budget") - F.coalesce(F.sum(F.when(F.col("full"), F.col("cap"))).over(everything), F.lit(0)))
    t = t.withColumn("over", F.col("all_weight") - F.coalesce(F.sum(F.when(F.col("full"), F.col("weight"))).over(everything), F.lit(0)))
    target = F.when(F.col("full"), F.col("cap").cast("double")).otherwise((F.col("weight") * F.col("left")).cast("double") / F.col("over"))
    return t.select("source", "sid", "weight", "source_size", target.alias("target"))


def queued(
    docs: DataFrame, id_col: str, text_col: str, source_col: str, weights: tuple[int, ...], max_epochs: int, share: float, seed: str, row_col: str | None
) -> DataFrame:
    """(id, row, source, size, source_size, sid, weight, rate, target, start) of every document, written once.

    ``start`` is the place in the shuffled source, in words, and ``rate`` the ticks of virtual time that a word takes."""
    draw = F.md5(F.concat_ws(":", F.coalesce(F.col(id_col).cast("string"), F.lit("null")), F.lit(seed)).cast("binary"))
    row = F.monotonically_increasing_id() if row_col is None else F.col(row_col)
    sized = staged(docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), word_count(F.col(text_col)).alias("size"), draw.alias("draw"), row.alias("row")), "mix-sizes")
    totals = staged(targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, max_epochs, share), "mix-targets")
    rows = sized.count()
    bits = min(BUCKET_BITS, max(0, math.ceil(math.log2(max(1, rows / BUCKET_ROWS)))))
    bucket = F.shiftright(F.conv(F.substring("draw", 1, 4), 16, 10).cast("int"), 16 - bits)
    known = bounded_join(sized.withColumn("_s", F.struct("source")), totals.withColumn("_s", F.struct("source")).drop("source"), "_s").drop("_s")
    known = known.withColumn("bucket", bucket)
    sums = known.groupBy("sid", "bucket").agg(F.sum("size").alias("held"))
    ahead = F.coalesce(F.sum("held").over(Window.partitionBy("sid").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    sums = sums.select("sid", "bucket", ahead.alias("ahead"))
    inside = F.sum("size").over(Window.partitionBy("sid", "bucket").orderBy("draw", "id", "size").rowsBetween(Window.unboundedPreceding, 0))
    placed = known.withColumn("start", inside - F.col("size")).join(sums, ["sid", "bucket"]).withColumn("start", F.col("start") + F.col("ahead"))
    rate = F.expr(f"{math.lcm(*weights)}L div weight")
    return staged(placed.select("id", "row", "source", "size", "source_size", "sid", "weight", rate.alias("rate"), "target", "start"), "mix-queue")


def packets(queue: DataFrame, most_words: int, max_epochs: int) -> DataFrame:
    """(tick, sid, words): every packet of the queue with its virtual finish time."""
    copies = queue.where("size > 0").withColumn("epoch", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(max_epochs - 1).cast("long"))))
    parts = copies.withColumn("part", F.explode(F.expr(f"sequence(0L, (size - 1) div {most_words}L)")))
    done = F.expr(f"least(size, (part + 1) * {most_words}L)")
    return parts.select(((F.col("epoch") * F.col("source_size") + F.col("start") + done) * F.col("rate")).alias("tick"), "sid", (done - F.col("part") * most_words).alias("words"))


def cut_of(sent: DataFrame, budget: int) -> tuple[int, int, int]:
    """(tick, sid, words) of the packet at which the budget ends, and its words that are still taken.

    Totals of at most ``RANGES`` ranges of virtual time come to the driver in each round."""
    low, high = 0, (sent.agg(F.max("tick")).first()[0] or 0) + 1
    left = budget
    while True:
        width = -(-(high - low) // RANGES)
        inside = sent.where((F.col("tick") >= low) & (F.col("tick") < high))
        found = inside.groupBy(F.expr(f"(tick - {low}L) div {width}L").alias("range")).agg(F.sum("words").alias("words"), F.count("*").alias("n")).collect()
        for r in sorted(found, key=lambda r: r.range):
            if r.words >= left:
                low, high = low + r.range * width, min(high, low + (r.range + 1) * width)
                break
            left -= r.words
        else:
            return high, 0, 0  # the queues end before the budget
        if r.n <= LEAF or high - low == 1:
            break
    order = Window.orderBy("tick", "sid")
    leaf = sent.where((F.col("tick") >= low) & (F.col("tick") < high)).withColumn("total", F.sum("words").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    last = leaf.where(F.col("total") >= left).orderBy("tick", "sid").first()
    return last.tick, last.sid, left - (last.total - last.words)


def allotments(
    spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
    weights: tuple[int, ...] = (5, 2, 1), max_epochs: int = 3, share: float = 1.0, seed: str = "mix", row_col: str | None = None,
) -> DataFrame:
    """One row per document: id, row, source, size, source_size, weight, rate, target, start, copies, taken.

    ``copies`` lists the words taken of each repetition: the document's packets before the cut of the sequence."""
    queue = queued(docs, id_col, text_col, source_col, weights, max_epochs, share, seed, row_col)
    budget = math.floor((queue.agg(F.sum("size")).first()[0] or 0) * share)
    most_words = max(1, budget // PACKETS)
    tick, sid, part = cut_of(packets(queue, most_words, max_epochs), budget) if budget else (0, 0, 0)
    reached = f"(if(sid < {sid}, {tick}L, {tick}L - 1) div rate - (e * source_size + start))"
    whole = f"if({reached} >= size, size, greatest(0L, {reached}) div {most_words}L * {most_words}L)"
    end = f"({tick}L div rate - (e * source_size + start))"
    at_cut = f"(sid = {sid} and {tick}L % rate = 0 and {end} > 0 and ({end} = size or ({end} < size and {end} % {most_words}L = 0)))"
    words = F.expr(f"transform(sequence(0L, {max_epochs - 1}L), e -> {whole} + if({at_cut}, {part}L, 0L))")
    taken = F.expr("aggregate(copies, 0L, (a, x) -> a + x)")
    named = queue.withColumn("copies", words).withColumn("taken", taken)
    return named.select(F.col("id").alias(id_col), "row", F.col("source").alias(source_col), "size", "source_size", "weight", "rate", "target", "start", "copies", "taken")


def mixed_documents(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **options) -> DataFrame:
    """The documents of the mix with the columns of ``docs``, a row per copy; the one at a cut is shortened.

    Copies are range-sorted by virtual finish time: partitions follow each other, and rows
    inside them are in order. Documents without words weigh nothing and stay once, at their
    place in the source. Rows are told apart by numbers, so repeated ids are separate documents."""
    held, row = numbered(docs, "mix-docs")
    once = F.when(F.col("size") == 0, F.array(F.lit(0).cast("long"))).otherwise(F.col("copies"))
    tick = (F.col("epoch") * F.col("source_size") + F.col("start") + F.col("words")) * F.col("rate")

    def copies() -> DataFrame:
        share = allotments(spark, held, id_col, text_col, source_col, row_col=row, **options)
        listed = share.select("row", "size", "source_size", "start", "rate", F.posexplode(once).alias("epoch", "words"))
        return listed.where("size = 0 or words > 0").select("row", "size", "words", tick.alias("tick"))

    plan = settled("mix-plan", copies)
    # ranges are drawn on the slim plan, since repartitionByRange would join all texts once more to sample them
    parts = int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
    cuts = sorted(set(plan.agg(F.percentile_approx("tick", [i / parts for i in range(1, parts)] or [0.5], 10_000)).first()[0] or []))
    bounds = F.array(*map(F.lit, cuts)) if cuts else F.array().cast("array<bigint>")
    mix, place = free_name(held.columns, "mix"), free_name(held.columns, "place")
    keyed = plan.select(F.col("row").alias(row), F.struct("tick", "size", "words").alias(mix), F.size(F.filter(bounds, lambda cut: cut < F.col("tick"))).alias(place))
    ordered = held.join(keyed, row).repartitionById(len(cuts) + 1, place).sortWithinPartitions(f"{mix}.tick", row)
    text = F.when(F.col(f"{mix}.words") >= F.col(f"{mix}.size"), F.col(text_col)).otherwise(leading_words(F.col(text_col), F.col(f"{mix}.words")))
    return ordered.withColumn(text_col, text).select(*docs.columns)


def op3_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return allotments(spark, docs).select("doc_id", "size", "source_size", "target", "taken")


OP3_SQL = r"""
WITH d AS (
  SELECT doc_id, source, md5(doc_id::VARCHAR || ':mix') AS draw,
         len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size
  FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
n AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS sid FROM s),
w AS (SELECT *, [5, 2, 1][(sid % 3 + 1)::INT]::BIGINT AS weight, 3 * source_size AS cap FROM n),
b AS (
  SELECT *, sum(source_size) OVER () AS budget, sum(weight) OVER () AS all_weight,
         coalesce(sum(cap) OVER p, 0) AS spent, coalesce(sum(weight) OVER p, 0) AS gone
  FROM w WINDOW p AS (ORDER BY cap / weight, sid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
f AS (SELECT *, cap * (all_weight - gone) <= weight * (budget - spent) AS is_full FROM b),
t AS (
  SELECT source, sid, source_size,
         CASE WHEN is_full THEN cap::DOUBLE
              ELSE (weight * (budget - coalesce(sum(CASE WHEN is_full THEN cap END) OVER (), 0)))::DOUBLE
                   / (all_weight - coalesce(sum(CASE WHEN is_full THEN weight END) OVER (), 0))::DOUBLE END AS target
  FROM f),
r AS (
  SELECT d.doc_id, d.size, t.sid, t.source_size, t.target, 10 // [5, 2, 1][(t.sid % 3 + 1)::INT] AS rate,
         row_number() OVER (ORDER BY d.doc_id) AS row,
         sum(d.size) OVER (PARTITION BY t.sid ORDER BY d.draw, d.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - d.size AS start
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
m AS (SELECT sum(size)::BIGINT AS budget, greatest(1, sum(size)::BIGINT // 1048576) AS most_words FROM d),
e AS (SELECT r.*, epoch, unnest(generate_series(0, (size - 1) // most_words)) AS part, most_words, budget
      FROM r, m, (SELECT unnest(generate_series(0, 2)) AS epoch) WHERE size > 0),
p AS (SELECT row, sid, (epoch * source_size + start + least(size, (part + 1) * most_words)) * rate AS tick,
             least(size, (part + 1) * most_words) - part * most_words AS words, budget FROM e),
o AS (SELECT row, words, budget, sum(words) OVER (ORDER BY tick, sid ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS total FROM p),
k AS (SELECT row, sum(greatest(0, least(words, budget - (total - words))))::BIGINT AS taken FROM o GROUP BY row)
SELECT doc_id, size, source_size, target, coalesce(taken, 0)::BIGINT AS taken
FROM r LEFT JOIN k USING (row)
"""

QUERIES = {"op3_source_mixing": op3_source_mixing}
SQL = {"op3_source_mixing": OP3_SQL}
