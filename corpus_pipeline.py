"""The corpus pipeline: five stages, each one operator applied to all documents that the one before it kept.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; the driver of the pipeline writes it as Parquet and
reads it again as the next stage's documents.  All but the last return the columns of ``documents``.

Every row is judged by itself, also where doc_id is null or repeated; rows that repeat an id and text are copies of
each other for the near-copy stage.  A null or empty text is kept by the first four stages; the mix takes nothing of
it.  Empty tables give empty results.  Other columns are carried through and play no part.  Texts are judged whole.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from domsearch.llm.decontamination import find_contained
from domsearch.llm.frames import with_ids, written
from domsearch.llm.ngram_join import jaccard_components
from domsearch.llm.secret_scan import scan_secrets
from domsearch.llm.source_mix import mix_sources
from domsearch.llm.toxicity import ToxicityModel


def _without(docs: DataFrame, judge: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``docs`` less the rows whose ids ``judge`` returns; it gets rows with distinct ids.

    Where doc_id is null or repeated, rows are numbered in the order of doc_id (null last) and text, in a written
    table, and judged by their numbers.
    """
    if docs.groupBy("doc_id").count().where("count > 1 or doc_id is null").isEmpty():
        return with_ids(docs, written(judge(docs).select("doc_id").distinct(), "removed"), "doc_id", "left_anti").select(docs.columns)
    key = "row"
    while key in docs.columns:
        key += "_"
    rows = written(docs.orderBy(F.col("doc_id").asc_nulls_last(), "text").withColumn(key, F.monotonically_increasing_id()), "rows")
    removed = judge(rows.drop("doc_id").withColumnRenamed(key, "doc_id")).select(F.col("doc_id").alias(key)).distinct()
    return with_ids(rows, written(removed, "removed"), key, "left_anti").select(docs.columns)


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the ordinal model holds for toxic go."""
    model = ToxicityModel.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return _without(docs, lambda rows: model.score(rows).where("toxic"))


def ngram_jaccard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the smallest id stays."""
    return _without(docs, lambda rows: jaccard_components(rows).where("doc_id <> component_id"))


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return _without(docs, lambda rows: find_contained(rows, items))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a secret go."""
    return _without(docs, lambda rows: scan_secrets(rows).where("n_assign + n_access + n_hex + n_linked > 0"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What the mix takes of each remaining document; documents of which it takes nothing go."""
    return mix_sources(docs).where(F.col("taken") > 0).select("doc_id", "source", "size", "taken", F.transform("draws", lambda d: d["shard"]).alias("shards"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", toxicity),
    ("n-gram Jaccard join", ngram_jaccard),
    ("benchmark decontamination", decontamination),
    ("secret scans", secrets),
    ("mixing sources to target weights", mixing),
]

ORACLE_SQL = None  # a fitted model and hash orders can't be expressed; tests/llm holds brute-force versions


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return STAGES[-1][1](spark, docs, sf_dir)
