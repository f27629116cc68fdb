"""Language identification by Bayesian evidence fusion.

Four kinds of evidence about a page or document are multiplied: the likelihood of its
text under byte-trigram models of the languages; the declared language (markup or
metadata); the suffix of its address; and a prior from its host. The tables of declared
languages and suffixes given the language, and the host priors, are estimated by grouped
aggregation of the text posteriors over all rows. Host priors are smoothed along a
hierarchy - host, its parent domain, its suffix, all rows - each level shrinking to the
one above by a fixed pseudo-count. A row's own contribution is taken out of its host counts.

The languages are the declared tags of at least ``support`` rows, however many there are. The
trigram models are fitted on a bounded sample of the rows of each: at most ``sample_rows``
rows, of long texts ``sample_chars`` characters in windows spread over all of the text, counted
by executors. A model takes ``BUCKETS`` floats per language.

Defined results: rows whose text has no letters and no declared language, and rows whose
best posterior is below ``least``, are rejected (lang null); null text is empty text,
decided by the other evidence; null or unknown declared languages and addresses are no
evidence. Without any declared language in the table all rows are rejected. Ties go to
the language first by code point. Very long texts are read whole, in blocks. Repeated rows and rows
of one id are told apart by number. Empty tables give empty results. Other columns are kept, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from pathmeet.joins import bounded_join, hot_join
from pathmeet.llm.labelled import excerpt
from pathmeet.rows import numbered, without_rows
from pathmeet.scratch import settled, staged

#: Buckets of hashed trigrams; the odd constant spreads them (Fibonacci hashing).
BUCKETS, SPREAD = 1 << 15, 2654435769
#: Trigrams overlap, so a text counts as this share of its trigrams, and at most as this many.
WEIGHT, MOST_EVIDENCE = 0.3, 60.0
#: Pseudo-counts of a smoothing level and of the cells of the declared-language and suffix tables.
SHRINK, CELL = 10.0, 0.5

LOWER = np.arange(256, dtype=np.uint32)
LOWER[0x41:0x5B] += 32
IS_LETTER = np.zeros(256, bool)
IS_LETTER[0x41:0x5B] = IS_LETTER[0x61:0x7B] = IS_LETTER[0x80:] = True


#: Bytes of a text that are read at once.
BLOCK = 1 << 20


def trigrams(raw: bytes) -> np.ndarray:
    """Hashed trigrams of the lower-case text; runs without letters are one space."""
    data = np.frombuffer(raw, np.uint8)
    letter = IS_LETTER[data]
    keep = letter | np.concatenate([[False], letter[:-1]])[: len(letter)]
    b = np.concatenate([[32], np.where(letter, LOWER[data], 32)[keep], [32]]).astype(np.uint32)
    if len(b) < 3 or not letter.any():
        return np.zeros(0, np.int64)
    return ((((b[:-2] << 16) | (b[1:-1] << 8) | b[2:]) * np.uint32(SPREAD)) >> np.uint32(17)).astype(np.int64)


def trigram_counts(text: str | None) -> np.ndarray:
    """How often each bucket occurs; a long text is counted block by block, so memory does not grow with it."""
    raw = (text or "").encode()
    total = np.zeros(BUCKETS, np.int64)
    for at in range(0, len(raw), BLOCK):
        total += np.bincount(trigrams(raw[at : at + BLOCK]), minlength=BUCKETS)
    return total


class TextModel:
    """Log-likelihoods of trigrams by language."""

    def __init__(self, langs: list[str], counts: np.ndarray):
        self.langs = langs
        smooth = counts + 0.1
        self.table = np.log(smooth / smooth.sum(axis=1, keepdims=True)).astype(np.float32).T.copy() if langs else np.zeros((BUCKETS, 0), np.float32)

    def log_likelihood(self, text: str | None) -> np.ndarray:
        """Relative to the best language, weighted for overlap and bounded."""
        counts = trigram_counts(text)
        there = np.flatnonzero(counts)
        if not len(there):
            return np.zeros(len(self.langs))
        total = counts[there].astype(np.float64) @ self.table[there].astype(np.float64) * WEIGHT
        return np.maximum(total - total.max(), -MOST_EVIDENCE)


def visible_text(html: Column) -> Column:
    """The text of a page: scripts, styles, comments and tags become spaces."""
    bare = F.regexp_replace(F.coalesce(html, F.lit("")), r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->", " ")
    return F.regexp_replace(F.regexp_replace(bare, r"<[^>]*>", " "), r"&[a-zA-Z]+;", " ")


def declared_in(html: Column) -> Column:
    """The primary language tag of the html element, null if there is none."""
    tag = F.lower(F.regexp_extract(html, r"(?is)<html\b[^>]*?\blang\s*=\s*[\"']?([a-zA-Z]{2,3})\b", 1))
    return F.when(tag != "", tag)


def address_parts(url: Column) -> dict[str, Column]:
    """host, parent domain (two last labels) and suffix of an address; null without a host."""
    host = F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]+)", 1))
    host = F.when(host != "", host)
    return {"host": host, "domain": F.substring_index(host, ".", -2), "suffix": F.substring_index(host, ".", -1)}


def _fitted(slim: DataFrame, rows: DataFrame, support: int, sample_rows: int, sample_chars: int) -> TextModel:
    """Fits on at most ``sample_rows`` rows of each language that at least ``support`` rows declare.

    The sample is drawn from ``slim`` (written; declared, row) by a hash, so that some four times as many rows as
    wanted reach the sort of a language; texts of ``rows`` (declared, row, text) are extracted for drawn rows only, and
    executors count the trigrams."""
    named = slim.where("declared is not null")
    langs = staged(named.groupBy("declared").agg(F.count("*").alias("n")).where(F.col("n") >= support), "lang-declared")
    names = sorted(r.declared for r in langs.select("declared").collect())
    if not names:
        return TextModel([], np.zeros((0, BUCKETS)))
    hashed = F.xxhash64("row")
    share = F.lit(4.0 * sample_rows) / F.col("n")
    likely = bounded_join(named.select("declared", "row"), langs, "declared").where(F.pmod(hashed, F.lit(1 << 30)) < share * (1 << 30))
    ranked = likely.withColumn("place", F.row_number().over(Window.partitionBy("declared").orderBy(hashed, "row")))
    picked = staged(ranked.where(F.col("place") <= sample_rows).select("row"), "lang-picked")
    sampled = bounded_join(rows, picked, "row", "left_semi").select("declared", excerpt(F.col("text"), sample_chars).alias("text"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for lang, one in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                total[lang] = total.get(lang, 0) + trigram_counts(one)
        for lang, counts in total.items():
            there = np.flatnonzero(counts)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(there), pa.string()), pa.array(there, pa.int64()), pa.array(counts[there], pa.int64())], names=["declared", "bucket", "n"])

    found = sampled.mapInArrow(count, "declared string, bucket long, n long").groupBy("declared", "bucket").agg(F.sum("n").alias("n")).toArrow()
    place = {lang: i for i, lang in enumerate(names)}
    counts = np.zeros((len(names), BUCKETS))
    if found.num_rows:
        at = [place[x] for x in found.column("declared").to_pylist()]
        counts[at, found.column("bucket").to_numpy()] = found.column("n").to_numpy()
    return TextModel(names, counts)


def sums(rows: DataFrame, key: list[str], k: int) -> DataFrame:
    """The key, ``counts`` (sum of the posteriors ``p`` of its rows) and ``size`` (its rows)."""
    grouped = rows.groupBy(*key).agg(F.array(*(F.sum(F.col("p")[i]) for i in range(k))).alias("counts"), F.count("*").alias("size"))
    return staged(grouped, "lang-sums")


def identify(
    spark: SparkSession, table: DataFrame, id: Column, text: Column, declared: Column, host: Column, domain: Column | None = None, suffix: Column | None = None,
    least: float = 0.5, sample_rows: int = 500, sample_chars: int = 20_000, support: int = 3, row_col: str | None = None,
) -> DataFrame:
    """One row per input row: id, row, lang (null: rejected), posterior, text_lang, declared, host.

    ``row`` tells repeated ids apart. The tables of a key are joined without sending a hot key through a shuffle."""
    none = F.lit(None).cast("string")
    if row_col is None:
        table, row_col = numbered(table, "lang-rows")
    rows = table.select(
        id.alias("id"), F.coalesce(text, F.lit("")).alias("text"), F.lower(declared).alias("declared"), host.alias("host"),
        (none if domain is None else domain).alias("domain"), (none if suffix is None else suffix).alias("suffix"), F.col(row_col).alias("row"),
    )
    slim = staged(rows.select("declared", "row"), "lang-slim")
    named = rows.select("declared", "row", "text")
    model = _fitted(slim, named, support, sample_rows, sample_chars)
    langs, k = model.langs, len(model.langs)
    if not k:
        return rows.select("id", "row", none.alias("lang"), F.lit(0.0).alias("posterior"), none.alias("text_lang"), "declared", "host")

    @F.arrow_udf(T.ArrayType(T.DoubleType()))
    def likelihood(texts: pa.Array) -> pa.Array:
        return pa.array([model.log_likelihood(t).tolist() for t in texts.to_pylist()], pa.list_(pa.float64()))

    soft = F.transform("ll", lambda x: F.exp(x))  # the best language has 0
    total = F.aggregate("e", F.lit(0.0), lambda a, x: a + x)
    read = rows.select("id", "row", "declared", "host", "domain", "suffix", F.rlike("text", F.lit(r"\p{L}")).alias("letters"), likelihood("text").alias("ll"))
    read = read.withColumn("e", soft).withColumn("p", F.transform("e", lambda x: x / total)).drop("e")
    read = staged(read, "lang-evidence")
    whole = sums(read, [], k).first()
    overall = np.array([x or 0.0 for x in whole["counts"]]) + 1.0
    overall /= overall.sum()

    known, rows_in_all = read, whole["size"]
    tables = {}
    for key in ("declared", "suffix", "domain", "host"):
        counts = sums(read.where(F.col(key).isNotNull()), [key], k)
        if key in ("declared", "suffix"):
            at = counts.agg(F.array(*(F.sum(F.col("counts")[i]) for i in range(k))).alias("t"), F.count("*").alias("values")).first()
            tables[key] = np.array([x or 0.0 for x in at.t or [0.0] * k]) + CELL * max(1, at["values"])
        known = hot_join(known, counts.select(key, F.col("counts").alias(f"{key}_counts"), F.col("size").alias(f"{key}_size")), [key], f"{key}_size", rows_in_all)

    kind = T.StructType([T.StructField("best", T.IntegerType()), T.StructField("posterior", T.DoubleType())])

    @F.arrow_udf(kind)
    def fused(ll: pa.Array, p: pa.Array, declared: pa.Array, suffix: pa.Array, domain: pa.Array, host: pa.Array) -> pa.Array:
        n = len(ll)
        own = _matrix(p, n, k)[0]
        log = _matrix(ll, n, k)[0]
        found = {"declared": _matrix(declared, n, k), "suffix": _matrix(suffix, n, k), "domain": _matrix(domain, n, k), "host": _matrix(host, n, k)}
        for key, totals in tables.items():
            counts, there = found[key]
            log = log + np.where(there[:, None], np.log((counts + CELL) / totals), 0.0)
        prior = np.tile(overall, (n, 1))
        for key in ("suffix", "domain", "host"):
            counts, there = found[key]
            rest = np.where(there[:, None], np.maximum(0.0, counts - own), 0.0)
            prior = (rest + SHRINK * prior) / (rest.sum(axis=1, keepdims=True) + SHRINK)
        log = log + np.log(prior)
        weight = np.exp(log - log.max(axis=1, keepdims=True))
        posterior = weight / weight.sum(axis=1, keepdims=True)
        best = posterior.argmax(axis=1)
        return pa.StructArray.from_arrays([pa.array(best, pa.int32()), pa.array(posterior[np.arange(n), best], pa.float64())], names=["best", "posterior"])

    name_of = F.array(*map(F.lit, langs))
    evidence = F.col("letters") | F.col("declared").isNotNull()
    judged = known.withColumn("f", fused("ll", "p", *(f"{x}_counts" for x in ("declared", "suffix", "domain", "host"))))
    return judged.select(
        "id", "row", F.when(evidence & (F.col("f.posterior") >= least), F.get(name_of, F.col("f.best"))).alias("lang"), F.col("f.posterior").alias("posterior"),
        F.when(F.col("letters"), F.get(name_of, (F.array_position("ll", F.lit(0.0)) - 1).cast("int"))).alias("text_lang"), "declared", "host",
    )


def _matrix(lists: pa.Array, n: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows of ``k`` numbers and which of them are there; zeros for nulls."""
    there = ~np.asarray(lists.is_null().to_numpy(zero_copy_only=False), bool)
    out = np.zeros((n, k))
    out[there] = lists.drop_null().flatten().to_numpy(zero_copy_only=False).reshape(-1, k)
    return out, there


def pages_languages(spark: SparkSession, pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", **options) -> DataFrame:
    """Languages of web pages from visible text, html language, address suffix and host."""
    parts = address_parts(F.col(url_col))
    return identify(spark, pages, F.col(id_col), visible_text(F.col(html_col)), declared_in(F.col(html_col)), **parts, **options)


def documents_languages(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", declared_col: str = "lang", source_col: str = "source", **options) -> DataFrame:
    """Languages of documents; the source takes the place of the host."""
    return identify(spark, docs, F.col(id_col), F.col(text_col), F.col(declared_col), F.col(source_col), **options)


def keep_identified(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """The rows of ``docs`` with a language, with all their columns."""
    held, row = numbered(docs, "lang-docs")
    lost = lambda: documents_languages(spark, held, id_col, row_col=row, **options).where("lang is null").select(F.col("row").alias(row))
    return without_rows(held, settled("lang-gone", lost), row)


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pages_languages(spark, spark.read.parquet(f"{sf_dir}/pages.parquet"))
    return found.select(F.col("id").alias("page_id"), "lang", "posterior", "text_lang", "declared", "host")


QUERIES = {"op6_language_id": op6_language_id}
SQL: dict[str, str] = {}
