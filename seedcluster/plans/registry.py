"""All queries and their SQL."""

from __future__ import annotations

from . import experiments, method_queries, relational, streams  # noqa: F401  they add to the registry
from .queries import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
