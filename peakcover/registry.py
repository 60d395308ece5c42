"""All queries of the placement methods by name, and the SQL with the same result."""

from __future__ import annotations

from .plans.workloads import ORACLE_SQL, QUERIES

__all__ = ["ORACLE_SQL", "QUERIES"]
