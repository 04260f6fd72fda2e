"""Conversions between containment t and Jaccard s for set sizes x and q, and the thresholds built on them."""

from __future__ import annotations

from pyspark.sql import Column

from .scores import _d


def jaccard_of(t, x, q) -> Column:
    return _d(t) / (_d(x) / _d(q) + 1 - _d(t))


def containment_of(s, x, q) -> Column:
    return (_d(x) / _d(q) + 1) * _d(s) / (1 + _d(s))


def conservative_threshold(t, u, q) -> Column:
    """The Jaccard threshold that loses no set of at most ``u`` values with containment ``t``."""
    return jaccard_of(t, u, q)


def effective_threshold(t, x, q, u) -> Column:
    """The containment at which a set of x values passes the conservative threshold of its partition."""
    return (_d(x) + _d(q)) * _d(t) / (_d(u) + _d(q))


def least_size(t, u, q) -> Column:
    """Size below which no set of a partition passes the ideal filter."""
    return _d(t) * _d(q) * _d(q) / (_d(u) + _d(q) - _d(t) * _d(q))
