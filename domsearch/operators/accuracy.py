"""Accuracy of answers against the truth, and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def per_query(answer: DataFrame, truth: DataFrame, keys: tuple[str, ...] = ("index_id", "t_star", "query_id")) -> DataFrame:
    """Counts, precision and recall of each query.  Both sides carry ``keys`` and domain_id; one shuffle of their union."""
    marked = answer.select(*keys, "domain_id", F.lit(1).alias("a"), F.lit(0).alias("b")).unionByName(truth.select(*keys, "domain_id", F.lit(0).alias("a"), F.lit(1).alias("b")))
    pairs = marked.groupBy(*keys, "domain_id").agg(F.max("a").alias("a"), F.max("b").alias("b"))
    return scored(pairs.groupBy(*keys).agg(F.sum("a").alias("n_answer"), F.sum("b").alias("n_truth"), F.sum(F.col("a") * F.col("b")).alias("n_hit")))


def scored(counts: DataFrame) -> DataFrame:
    """Precision and recall beside the counts n_answer, n_truth and n_hit."""
    precision = F.when(F.col("n_answer") == 0, F.lit(1.0)).otherwise(F.col("n_hit") / F.col("n_answer"))
    recall = F.when(F.col("n_truth") > 0, F.col("n_hit") / F.col("n_truth"))
    return counts.withColumn("precision", precision).withColumn("recall", recall)


def f_beta(p: Column, r: Column, beta: float) -> Column:
    top = (1 + beta * beta) * p * r
    return F.when(p + r > 0, top / (beta * beta * p + r)).otherwise(F.lit(0.0))


def summary(rows: DataFrame, keys: tuple[str, ...] = ("index_id", "t_star")) -> DataFrame:
    """Means per index and threshold; empty answers count for recall and the empty share, not for precision.

    f1 and f05 are those of the mean precision and recall; mean_f1 and mean_f05 are means over queries.
    """
    each = lambda beta: F.avg(F.when(F.col("recall").isNotNull(), f_beta(F.col("precision"), F.col("recall"), beta)))
    means = rows.groupBy(*keys).agg(
        F.count("*").alias("n_queries"), F.avg(F.when(F.col("n_answer") > 0, F.col("precision"))).alias("p"), F.avg("recall").alias("r"),
        F.avg((F.col("n_answer") == 0).cast("double")).alias("empty"), F.avg("n_answer").alias("mean_answer"), each(1.0).alias("mean_f1"), each(0.5).alias("mean_f05"),
    )
    p = F.coalesce(F.col("p"), F.lit(1.0))
    return means.select(
        *keys, "n_queries", F.round(p, 6).alias("precision"), F.round("r", 6).alias("recall"), F.round(f_beta(p, F.col("r"), 1.0), 6).alias("f1"),
        F.round(f_beta(p, F.col("r"), 0.5), 6).alias("f05"), F.round("empty", 6).alias("empty_share"), F.round("mean_answer", 6).alias("mean_answer"),
        F.round("mean_f1", 6).alias("mean_f1"), F.round("mean_f05", 6).alias("mean_f05"),
    )
