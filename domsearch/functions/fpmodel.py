"""Expected false positives of a size interval, and the cost of a partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .scores import _d


def p_false_positive(x, u, q, t=None, capped: bool = False) -> Column:
    """Chance that a set of x values, containment uniform, is a false positive.  Capped: containment can't exceed x/q."""
    if not capped:
        return (_d(u) - _d(x)) / (_d(u) + _d(q))
    most = F.least(_d(t), _d(x) / _d(q))
    effective = (_d(x) + _d(q)) * _d(t) / (_d(u) + _d(q))
    return F.greatest(F.lit(0.0), most - effective) / most


def fp_uniform(n, low, u, q) -> Column:
    return _d(n) * (_d(u) - _d(low) + 1) / (2 * (_d(u) + _d(q)))


def fp_bound(n, low, u) -> Column:
    """M of an interval: bound of its expected false positives for every query."""
    return _d(n) * (_d(u) - _d(low) + 1) / (2 * _d(u))


def expected_fp(hist: DataFrame, bounds: DataFrame, q: int) -> DataFrame:
    """(part_id, n_domains, expected_fp): sums over the sizes that occur; ``bounds`` is a handful of rows and broadcast."""
    joined = hist.join(F.broadcast(bounds.select("part_id", "size_lo", "size_hi_excl")), (F.col("size") >= F.col("size_lo")) & (F.col("size") < F.col("size_hi_excl")))
    return joined.groupBy("part_id").agg(F.sum("n_domains").alias("n_domains"), F.sum(F.col("n_domains") * p_false_positive(F.col("size"), F.col("size_hi_excl"), F.lit(q))).alias("expected_fp"))


def cost(hist: DataFrame, bounds: DataFrame, q: int) -> DataFrame:
    """Cost of a partitioning: false positives of its worst interval."""
    return expected_fp(hist, bounds, q).agg(F.max("expected_fp").alias("cost"), F.sum("expected_fp").alias("total_fp"))


def m_bound(bounds: DataFrame) -> DataFrame:
    return bounds.withColumn("m", fp_bound(F.col("n_domains"), F.col("size_lo"), F.col("size_hi_excl")))
