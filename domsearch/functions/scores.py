"""Relevance scores of a pair of sets from the size of their overlap and their own sizes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _d(c: Column | float) -> Column:
    return (c if isinstance(c, Column) else F.lit(c)).cast("double")


def containment(overlap: Column, q: Column) -> Column:
    """Share of the query that the other set holds; not symmetric."""
    return _d(overlap) / _d(q)


def jaccard(overlap: Column, q: Column, x: Column) -> Column:
    return _d(overlap) / (_d(q) + _d(x) - _d(overlap))


def dice(overlap: Column, q: Column, x: Column) -> Column:
    return 2 * _d(overlap) / (_d(q) + _d(x))


def cosine(overlap: Column, q: Column, x: Column) -> Column:
    return _d(overlap) / F.sqrt(_d(q) * _d(x))
