"""All queries of the engine by name."""

from . import relational, similarity, streams, workloads  # noqa: F401
from .registry import ORACLE, QUERIES

__all__ = ["ORACLE", "QUERIES"]
