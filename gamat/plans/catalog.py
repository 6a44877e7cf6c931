"""All queries of the engine with their oracles."""

from . import queries_matrix, queries_relational  # noqa: F401
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
