"""All named queries of the engine, without the training-data operators."""

from __future__ import annotations

from . import comparisons, methods, relational, streams, wider  # noqa: F401  each registers its queries
from .registry import QUERIES, SQL

__all__ = ["QUERIES", "SQL"]
