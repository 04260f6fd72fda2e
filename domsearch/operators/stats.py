"""Statistics of size distributions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def histogram(domains: DataFrame) -> DataFrame:
    """(size, n_domains, cum_before): one row for each size that occurs, small enough for a window over all of it."""
    hist = domains.groupBy("size").agg(F.count("*").alias("n_domains"))
    before = F.sum("n_domains").over(Window.orderBy("size").rowsBetween(Window.unboundedPreceding, -1))
    return hist.withColumn("cum_before", F.coalesce(before, F.lit(0)))


def log_histogram(domains: DataFrame) -> DataFrame:
    return domains.groupBy(F.floor(F.log2(F.col("size").cast("double")) + F.lit(1e-9)).cast("int").alias("log2_size")).agg(F.count("*").alias("n_domains"))


def skewness(domains: DataFrame) -> DataFrame:
    """Third central moment over the second to the power 3/2, of the population."""
    return domains.agg(F.count("*").alias("n_domains"), F.max("size").alias("max_size"), F.round(F.skewness("size"), 6).alias("skewness"))


def powerlaw_alpha(domains: DataFrame, least: int = 10) -> DataFrame:
    """Maximum-likelihood exponent of a discrete power law (continuous approximation)."""
    rows = domains.where(F.col("size") >= least)
    return rows.agg(F.count("*").alias("n_domains"), F.round(1 + F.count("*") / F.sum(F.log(F.col("size") / F.lit(least - 0.5))), 6).alias("alpha"))


def partition_stddev(meta: DataFrame) -> DataFrame:
    return meta.agg(F.count("*").alias("n_partitions"), F.round(F.stddev_pop("n_domains"), 6).alias("stddev"))
