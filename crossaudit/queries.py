"""All queries of the audit, and their SQL twins."""

from __future__ import annotations

from crossaudit.plans import corpus, leaks, matrix, streams, studies  # noqa: F401  (they register their queries)
from crossaudit.plans.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "flagship"]


def flagship(spark, sf_dir):
    return QUERIES["transfer_matrix"](spark, sf_dir)
