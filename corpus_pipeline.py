"""From raw documents to packed training sequences, in five stages.

Each stage takes (spark, docs, sf_dir) and works on all rows that the one before it kept.
All but the last return the columns of ``documents``; the last returns the pieces of the
packed sequences."""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession

from pathmeet.llm.exact_dedup import keep_first
from pathmeet.llm.language_id import keep_identified
from pathmeet.llm.packing import default_vocabulary, packed_pieces
from pathmeet.llm.shingle_links import keep_dissimilar
from pathmeet.llm.source_mixing import mixed_documents
from pathmeet.scratch import discard, drop_path, made, paths_of, staged


#: Scratch folders that the latest call of a stage left behind, by stage.
_left: dict[str, set[str]] = {}


def stage(work: Callable[[SparkSession, DataFrame, str], DataFrame]) -> Callable[[SparkSession, DataFrame, str], DataFrame]:
    """A stage that deletes what earlier stages left in the scratch folder.

    A stage's result is written before the next one is called, so its scratch tables have done their
    work by then; those that ``docs`` still reads (an unwritten result) stay."""

    @wraps(work)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        earlier = [name for name, _ in STAGES[: [name for name, _ in STAGES].index(work.__name__)]]
        for path in set().union(*(_left.pop(name, set()) for name in earlier)) - paths_of(docs):
            drop_path(spark, path)
        before = made()
        out = work(spark, docs, sf_dir)
        _left[work.__name__] = made() - before
        return out

    return run_stage


@stage
def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without an identifiable language."""
    return keep_identified(spark, docs)


@stage
def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each class of equal texts."""
    return keep_first(spark, docs)


@stage
def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each component of five-word shingle sets with similarity 0.8 or more.

    Candidates are groups of SimHash fingerprints linked by vantage-point shards, and min-hash
    bands for what lies beyond their radius; links count after an exact comparison."""
    return keep_dissimilar(spark, docs, words=5, least=0.8)


@stage
def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats, shortens or drops documents so that sources come near their target weights."""
    return mixed_documents(spark, docs)


@stage
def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs all documents into fixed windows; one row per piece."""
    return packed_pieces(docs, default_vocabulary())


STAGES = [
    ("language_id", language_id),
    ("exact_dedup", exact_dedup),
    ("simhash_near_dedup", simhash_near_dedup),
    ("source_mixing", source_mixing),
    ("packing", packing),
]

#: Fingerprints, trigram models and the tokenizer have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, work in STAGES[:-1]:
        before = docs
        docs = staged(work(spark, docs, sf_dir), name)
        discard(before)
    return STAGES[-1][1](spark, docs, sf_dir)
