"""Every query by name. Modules register theirs when they are imported."""

from . import dense, hybrid, measures, models, search, splits, streams, surface, texts, workloads  # noqa: F401
from .registry import ORACLE_SQL, QUERIES

__all__ = ["ORACLE_SQL", "QUERIES"]
