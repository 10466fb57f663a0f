"""All queries by name, and the SQL of those that SQL can express: every module of queries is imported here, and nowhere else."""

from __future__ import annotations

from . import experiments, further, methods, relational, stream_queries, studies, surface  # noqa: F401  each adds its own queries
from .base import ORACLE_SQL, QUERIES

__all__ = ["ORACLE_SQL", "QUERIES"]
