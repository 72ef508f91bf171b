"""All registered queries and oracles of the engine."""

from . import baseline_queries, core_queries, relational_queries, stream_queries  # noqa: F401
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
