"""Readers of the given tables."""

from crossaudit.sources.tables import TABLES, table

__all__ = ["TABLES", "table"]
