"""All registered queries of the engine, without the training-data subpackage."""

from . import methods, relational, workloads  # noqa: F401
from ..streaming import queries as _streams  # noqa: F401
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
