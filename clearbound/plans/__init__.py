"""Registered queries and the SQL that checks them."""

from . import audit, corpus, grading, judging  # noqa: F401
from .registry import ORACLES, QUERIES, WITHOUT_SQL

__all__ = ["ORACLES", "QUERIES", "WITHOUT_SQL"]
